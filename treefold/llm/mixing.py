"""Mixing sources to target weights by a multivariate-hypergeometric splitting tree.

Every source is laid out as one line of words in a seeded random order of its
documents, cut into blocks. A target asks for a number of block readings: each
full reading of the line is all its blocks, the rest is the first blocks of a
permutation. The tree splits the vector of these quotas among the output
shards, a multivariate hypergeometric draw at each node, so that every shard
gets an exact random share of every source; a shard then draws its share of
blocks from where the shards before it stopped in the permutation. A block that
no shard draws is not taken. Rows are shuffled in their shard.

Positions on a line come from prefix sums in three steps (buckets of bounded
size, groups of buckets, groups), so no source is ever sorted in one task.
"""

from __future__ import annotations

import math
from fractions import Fraction

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise, text_or_empty, word_count

WEIGHTS = (3, 1, 2)
SHARE = 1.5
MAX_REPEATS = 2
MAX_SOURCES = 100_000
BUCKET_ROWS = 512
GROUP_BUCKETS = 4096
BLOCK_WORDS = 4096
SHARD_WORDS = 1_000_000
MAX_BLOCKS = 100_000_000
#: Shares (sources x shards) that the driver and each executor hold; above it shards are larger.
MAX_SHARES = 4_000_000
_SEPARATED_WORD = r"[\x20\x09-\x0D]*[^\x20\x09-\x0D]+"


def share_out(sizes: list[int], weights: list[int], amount: Fraction, max_repeats: int = MAX_REPEATS) -> list[Fraction]:
    """Targets by weight, none above max_repeats times its size; what is cut off is shared again by weight."""
    targets = [Fraction(0)] * len(sizes)
    open_ = [i for i, s in enumerate(sizes) if s > 0]
    left = Fraction(amount)
    while open_:
        unit = left / sum(weights[i] for i in open_)
        capped = [i for i in open_ if unit * weights[i] > max_repeats * sizes[i]]
        if not capped:
            for i in open_:
                targets[i] = unit * weights[i]
            break
        for i in capped:
            targets[i] = Fraction(max_repeats * sizes[i])
            left -= targets[i]
        gone = set(capped)
        open_ = [i for i in open_ if i not in gone]
    return targets


def splitting_tree(quotas: list[int], shards: int, seed: int) -> np.ndarray:
    """blocks[source, shard]: exact quotas split down a binary tree of shards; every node's draw has its own seed."""
    out = np.zeros((len(quotas), shards), np.int64)
    stack = [(0, shards, np.asarray(quotas, np.int64))]
    while stack:
        low, high, here = stack.pop()
        if high - low == 1:
            out[:, low] = here
            continue
        middle = (low + high) // 2
        total = int(here.sum())
        part = total * (middle - low) // (high - low)
        rng = np.random.Generator(np.random.PCG64([seed, low, high]))
        left = rng.multivariate_hypergeometric(here, part, method="marginals") if total else here.copy()
        stack += [(low, middle, left), (middle, high, here - left)]
    return out


def _coprime(start: int, n: int) -> int:
    a = start % n or 1
    while math.gcd(a, n) != 1:
        a += 1
    return a


def _quota(words: int, size: int, block: int, step: int, turn: int) -> tuple[int, int, int]:
    """(blocks on the line, block readings wanted, words of the last one) for a target of so many words."""
    if not size:
        return 1, 0, 0
    n = -(-size // block)
    full, rest = divmod(words, size)
    if not rest:
        return n, full * n, block
    short = size - (n - 1) * block
    short_place = ((n - 1) * step + turn) % n

    def held(r: int) -> int:
        return r * block - (block - short if short_place < r else 0)

    r = -(-rest // block)
    while held(r) < rest:
        r += 1
    last = short if short_place == r - 1 else block
    return n, full * n + r, last - (held(r) - rest)


def _plan(by_source: list[tuple[str | None, int]], weights, share, max_repeats, block_words, shards, seed) -> tuple[list[tuple], int, int]:
    order = sorted(by_source, key=lambda x: (x[0] is None, x[0] or ""))
    sizes = [int(s) for _, s in order]
    use = [weights[i % len(weights)] for i in range(len(order))]
    targets = share_out(sizes, use, Fraction(share) * sum(sizes), max_repeats)
    words = [min(round(t), max_repeats * s) for t, s in zip(targets, sizes)]
    block = max(block_words, -(-sum(words) // MAX_BLOCKS))
    wanted = shards or -(-sum(words) // SHARD_WORDS)
    shards = max(1, min(wanted, MAX_SHARES // max(1, len(order))))
    lines = []
    for i, size in enumerate(sizes):
        n = max(1, -(-size // block))
        step = _coprime(int((seed * 1_000_003 + i * 7919) * 0.6180339887) + 1, n)
        turn = (seed * 31 + i * 17) % n
        lines.append((step, turn, *_quota(words[i], size, block, step, turn)))
    dealt = splitting_tree([line[3] for line in lines], shards, seed)
    rows = []
    for i, (source, _) in enumerate(order):
        step, turn, n, quota, last = lines[i]
        rows.append((i, source, sizes[i], float(targets[i]), n, quota, last, step, turn, [int(x) for x in np.cumsum(dealt[i])]))
    return rows, block, shards


def _running_totals(rows: DataFrame, line: str, size: str, order: list[str], buckets: int) -> DataFrame:
    """Adds __mix_at: the sum of size before each row of a line, in the order of __mix_bucket and then `order`."""
    rows = rows.withColumn("__mix_group", F.floor(F.col("__mix_bucket") / GROUP_BUCKETS))
    per_bucket = rows.groupBy(line, "__mix_group", "__mix_bucket").agg(F.sum(size).alias("__mix_n"))

    def before(*keys: str, by: str) -> F.Column:
        window = Window.partitionBy(*keys).orderBy(by).rowsBetween(Window.unboundedPreceding, -1)
        return F.coalesce(F.sum("__mix_n").over(window), F.lit(0))

    starts = per_bucket.withColumn("__mix_from", before(line, "__mix_group", by="__mix_bucket"))
    if buckets > GROUP_BUCKETS:
        per_group = per_bucket.groupBy(line, "__mix_group").agg(F.sum("__mix_n").alias("__mix_n")).withColumn("__mix_head", before(line, by="__mix_group"))
        starts = starts.join(per_group.drop("__mix_n"), [line, "__mix_group"]).withColumn("__mix_from", F.col("__mix_from") + F.col("__mix_head"))
    inside = Window.partitionBy(line, "__mix_bucket").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    placed = rows.withColumn("__mix_at", F.coalesce(F.sum(size).over(inside), F.lit(0)))
    joined = placed.join(starts.select(line, "__mix_bucket", "__mix_from"), [line, "__mix_bucket"])
    return joined.withColumn("__mix_at", F.col("__mix_at") + F.col("__mix_from")).drop("__mix_from", "__mix_group")


def mix(
    docs: DataFrame,
    weights: tuple[int, ...] = WEIGHTS,
    share: float = SHARE,
    max_repeats: int = MAX_REPEATS,
    block_words: int = BLOCK_WORDS,
    shards: int | None = None,
    seed: int = 29,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
    carry: tuple[str, ...] = (),
    prefix: str = "",
) -> DataFrame:
    """One row per input row: doc_id, size, source_size, target, taken, draws (all with the prefix), then the carried columns.

    size counts words (null text: 0). Sources by code point, null last, take the
    weights in turn; targets share `share` times all words. draws lists what the
    shards draw of the row: structs of epoch, block, shard, first_word, n_words.
    taken is their sum, at most max_repeats times the size; a source's sum is its
    target to the nearest word, as the last block drawn is cut there. shards:
    None takes one for each SHARD_WORDS words of the mix. Results depend on ids,
    texts and the seed alone. Rows that repeat an id take turns as rows of their
    own, null ids too. A document without words is never drawn. An empty table
    gives no rows. Sources are counted first; more than MAX_SOURCES are refused,
    and shards are made larger above MAX_SHARES shares, which bounds what the
    driver holds.
    """
    spark = docs.sparkSession
    names = {c: f"__mix_c{i}" for i, c in enumerate(carry)}
    rows = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        F.col(source_col).cast("string").alias("__mix_source"),
        word_count(F.col(text_col)).alias("size"),
        F.xxhash64(F.lit(seed), F.col(id_col).cast("long"), text_or_empty(text_col)).alias("__mix_h"),
        *[F.col(c).alias(n) for c, n in names.items()],
    )
    slim = materialise(rows, "mix-rows" if carry else "mix-sizes")
    found = slim.groupBy("__mix_source").agg(F.sum("size"), F.count(F.lit(1))).limit(MAX_SOURCES + 1).collect()
    if len(found) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources")
    plan, block, _ = _plan([(r[0], r[1]) for r in found], weights, share, max_repeats, block_words, shards, seed)
    buckets = max(1, -(-sum(r[2] for r in found) // BUCKET_ROWS))
    sources = spark.createDataFrame(
        plan, "src int, __mix_of string, source_size long, target double, blocks long, quota long, last_words long, step long, turn long, ends array<long>"
    )
    placed = (
        slim.join(F.broadcast(sources.select("src", "__mix_of")), F.col("__mix_source").eqNullSafe(F.col("__mix_of")))
        .drop("__mix_source", "__mix_of")
        .withColumn("__mix_bucket", F.pmod("__mix_h", F.lit(buckets)))
    )
    lined = _running_totals(placed, "src", "size", ["__mix_h", "doc_id", "size"], buckets).join(F.broadcast(sources.drop("__mix_of")), "src")

    begin = F.col("__mix_at")
    end = begin + F.col("size")

    def one_block(e, b):
        # every reading of the line goes through the blocks in the same permuted order
        place = e * F.col("blocks") + F.pmod(b * F.col("step") + F.col("turn"), F.col("blocks"))
        stop = b * F.lit(block) + F.when(place == F.col("quota") - 1, F.col("last_words")).otherwise(F.lit(block))
        first = F.greatest(begin, b * F.lit(block))
        return F.struct(
            e.alias("epoch"),
            b.alias("block"),
            F.size(F.filter("ends", lambda x: x <= place)).alias("shard"),
            (first - begin).alias("first_word"),
            (F.least(end, stop) - first).alias("n_words"),
        )

    blocks = F.sequence(F.floor(begin / F.lit(block)).cast("long"), F.floor((end - 1) / F.lit(block)).cast("long"))
    readings = F.sequence(F.lit(0), F.lit(max_repeats - 1))
    every = F.flatten(F.transform(readings, lambda e: F.transform(blocks, lambda b: one_block(e.cast("long"), b))))
    drawn_by_shard = F.filter(every, lambda d: (d["shard"] < F.size("ends")) & (d["n_words"] > 0))
    none = F.expr("cast(array() AS array<struct<epoch:bigint,block:bigint,shard:int,first_word:bigint,n_words:bigint>>)")
    drawn = lined.withColumn("draws", F.when(F.col("size") > 0, drawn_by_shard).otherwise(none))
    taken = F.aggregate("draws", F.lit(0).cast("long"), lambda s, x: s + x["n_words"])
    own = {"doc_id": F.col("doc_id"), "size": F.col("size"), "source_size": F.col("source_size"), "target": F.col("target"), "taken": taken, "draws": F.col("draws")}
    return drawn.select(*[c.alias(prefix + n) for n, c in own.items()], *[F.col(n).alias(c) for c, n in names.items()])


def mixed_documents(docs: DataFrame, text_col: str = "text", **options) -> DataFrame:
    """The mix itself, in the columns of docs: one row for each run of a document's words that one shard draws in one reading.

    Most documents lie in one block and come whole; one that blocks of several
    shards share, or that the last block is cut in, comes in parts, so every
    shard holds exactly the blocks that the tree gave it. Rows are dealt to
    shards and shuffled inside them; a shard too large for a task is split.
    """
    mixed = mix(docs, text_col=text_col, carry=tuple(docs.columns), prefix="__mix_", **options)
    text = F.col(text_col)

    def joins(run, d):
        return (run["epoch"] == d["epoch"]) & (run["shard"] == d["shard"]) & (run["first_word"] + run["n_words"] == d["first_word"])

    def longer(run, d):
        return F.struct(run["epoch"].alias("epoch"), run["shard"].alias("shard"), run["first_word"].alias("first_word"), (run["n_words"] + d["n_words"]).alias("n_words"))

    def add(runs, d):
        piece = F.struct(d["epoch"].alias("epoch"), d["shard"].alias("shard"), d["first_word"].alias("first_word"), d["n_words"].alias("n_words"))
        last = F.try_element_at(runs, F.lit(-1))
        grown = F.concat(F.slice(runs, 1, F.size(runs) - 1), F.array(longer(last, d)))
        return F.when((F.size(runs) > 0) & F.coalesce(joins(last, d), F.lit(False)), grown).otherwise(F.concat(runs, F.array(piece)))

    none = F.expr("cast(array() AS array<struct<epoch:bigint,shard:int,first_word:bigint,n_words:bigint>>)")
    # a draw is a whole document more often than not: the fold is for those of several blocks
    alone = F.transform("__mix_draws", lambda d: F.struct(d["epoch"].alias("epoch"), d["shard"].alias("shard"), d["first_word"].alias("first_word"), d["n_words"].alias("n_words")))
    split = F.exists("__mix_draws", lambda d: d["n_words"] < F.col("__mix_size"))
    drawn = mixed.withColumn("__mix_run", F.explode(F.when(split, F.aggregate("__mix_draws", none, add)).otherwise(alone))).drop("__mix_draws")
    first, count = F.col("__mix_run.first_word"), F.col("__mix_run.n_words")
    words = F.regexp_extract_all(text, F.lit(_SEPARATED_WORD), 0)
    cut = F.array_join(F.slice(words, (first + 1).cast("int"), count.cast("int")), "")
    out = drawn.withColumn(text_col, F.when(count < F.col("__mix_size"), cut).otherwise(text))
    out = out.withColumn("__mix_shard", F.col("__mix_run.shard")).withColumn("__mix_order", F.xxhash64(F.lit(7), "__mix_doc_id", F.col("__mix_run.epoch"), first))
    out = out.hint("rebalance", "__mix_shard").sortWithinPartitions("__mix_shard", "__mix_order")
    return out.select(*docs.columns)
