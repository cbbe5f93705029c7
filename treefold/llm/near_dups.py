"""N-gram Jaccard join with Bayesian candidate pruning.

Every text becomes its set of hashed word 5-grams and a MinHash signature.
Texts with the same set are one class. Classes that share a band of the
signature are candidates; signatures are then compared a few values at a time,
and a pair is dropped as soon as the posterior probability that its similarity
reaches the threshold falls below a tolerance. What remains is verified on the
whole sets.

No list of pairs is ever made. Within a band's bucket candidates are followed
as a graph search, which emits a spanning forest only. Its components are then
verified in blocks of bounded size, all pairs of a block pair at once, and each
block pair returns the number of links of each class and again a forest. So the
output grows with the number of documents, also for large groups of near
copies, and large buckets or components are dealt over many tasks.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import freed, materialise, prepare, text_or_empty

NGRAM = 5
THRESHOLD = 0.8
HASHES = 120
BAND_ROWS = 5
STEP = 20
TOLERANCE = 1e-4
BUCKET_BLOCK = 4096
BLOCK_CLASSES = 512
BLOCK_SHINGLES = 2_000_000
BROADCAST_ROWS = 100_000
_P = np.uint64(0x9E3779B97F4A7C15)


def _mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Shingler:
    """Sets of hashed word n-grams: words are runs of anything but ASCII white space, taken as they are."""

    def __init__(self, n: int = NGRAM, cache_words: int = 300_000):
        self.n = n
        self.cache_words = cache_words
        self.words: dict[bytes, int] = {}

    def _word_hashes(self, text: str) -> np.ndarray:
        import xxhash

        words = text.encode("utf-8", "surrogatepass").split()
        known = self.words
        try:
            return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
        except KeyError:
            pass
        if len(known) > self.cache_words:
            known.clear()
        digest = xxhash.xxh64_intdigest
        for word in set(words).difference(known):
            known[word] = digest(word)
        return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))

    def shingles(self, text: str) -> np.ndarray:
        """Sorted distinct hashes; a text of fewer than n words is one n-gram, one without words none."""
        words = self._word_hashes(text)
        if not len(words):
            return words
        span = min(self.n, len(words))
        count = len(words) - span + 1
        mixed = np.full(count, np.uint64(span), np.uint64)
        for i in range(span):
            mixed = mixed * _P + words[i : i + count]
        return np.unique(_mix(mixed))


@lru_cache(maxsize=4)
def _seeds(hashes: int) -> np.ndarray:
    return _mix(np.arange(1, hashes + 1, dtype=np.uint64) * _P) | np.uint64(1)


def signature(shingles: np.ndarray, hashes: int = HASHES) -> np.ndarray:
    """MinHash values cut to 16 bits; two sets agree in one by chance about once in 65,536."""
    seeds = _seeds(hashes)
    least = np.full(hashes, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(shingles), 1024):
        part = shingles[at : at + 1024]
        # multiply-shift keeps the high bits, so the order of products is a fair permutation for each seed
        np.minimum(least, (part[None, :] * seeds[:, None]).min(axis=1), out=least)
    return (_mix(least) & np.uint64(0xFFFF)).astype("<u2")


@lru_cache(maxsize=8)
def least_matches(hashes: int = HASHES, step: int = STEP, threshold: float = THRESHOLD, tolerance: float = TOLERANCE) -> tuple[tuple[int, int], ...]:
    """(values compared, fewest matches to go on): below it, P(similarity >= threshold | matches) < tolerance.

    With a uniform prior the posterior after m matches of n is Beta(m+1, n-m+1), whose
    upper tail at t is the binomial probability of at most m successes in n+1 trials of t.
    """
    from math import comb

    out = []
    for n in range(step, hashes + 1, step):
        tail, least = 0.0, n + 1
        for m in range(n + 1):
            tail += comb(n + 1, m) * threshold**m * (1 - threshold) ** (n + 1 - m)
            if tail >= tolerance:
                least = m
                break
        out.append((n, least))
    return tuple(out)


def survivors(one: np.ndarray, others: np.ndarray, rules=None) -> np.ndarray:
    """Indexes of the signatures in others that one may be similar to, by incremental comparison."""
    alive = np.arange(len(others))
    matches = np.zeros(len(others), np.int32)
    begin = 0
    for n, least in rules or least_matches():
        matches = matches + (others[alive, begin:n] == one[begin:n]).sum(axis=1, dtype=np.int32)
        go_on = matches >= least
        alive, matches = alive[go_on], matches[go_on]
        if not len(alive):
            break
        begin = n
    return alive


def _sign(hashes: int):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler()
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                signatures, keys, sizes = [], [], []
                for text in part.column("text").to_pylist():
                    s = shingler.shingles(text or "")
                    sizes.append(len(s))
                    if len(s):
                        signatures.append(signature(s, hashes).tobytes())
                        keys.append(_set_key(s))
                    else:
                        signatures.append(None)
                        keys.append(None)
                yield pa.RecordBatch.from_arrays(
                    [part.column("doc_id"), part.column("text_key"), pa.array(keys, pa.binary()), pa.array(sizes, pa.int64()), pa.array(signatures, pa.binary())],
                    ["doc_id", "text_key", "set_key", "n_shingles", "signature"],
                )

    return run


def _set_key(shingles: np.ndarray) -> bytes:
    import xxhash

    return xxhash.xxh3_128_digest(shingles.tobytes())


def _runs(batches: Iterable[pa.RecordBatch], keys: list[str]) -> Iterator[pa.Table]:
    """Rows that share the keys, from sorted input: tables of whole runs (of many keys each, but never part of one)."""
    held: list[pa.RecordBatch] = []

    def same(a: pa.RecordBatch, i: int, b: pa.RecordBatch, j: int) -> bool:
        return all(a.column(k)[i] == b.column(k)[j] for k in keys)

    for batch in batches:
        if not batch.num_rows:
            continue
        if held and not same(held[-1], held[-1].num_rows - 1, batch, 0):
            yield pa.Table.from_batches(held)
            held = []
        # the rows of the last key may go on in the next batch
        last = batch.num_rows - 1
        cut = last
        columns = [np.asarray(batch.column(k).to_numpy(zero_copy_only=False)) for k in keys]
        while cut > 0 and all(c[cut - 1] == c[last] for c in columns):
            cut -= 1
        if cut > 0:
            yield pa.Table.from_batches([*held, batch.slice(0, cut)])
            held = [batch.slice(cut)]
        else:
            held.append(batch)
    if held:
        yield pa.Table.from_batches(held)


def _groups(table: pa.Table, keys: list[str]) -> Iterator[tuple[int, int]]:
    """(start, stop) of each run of equal keys."""
    n = table.num_rows
    change = np.zeros(n, bool)
    change[0] = True
    for k in keys:
        c = table[k].to_numpy()
        change[1:] |= c[1:] != c[:-1]
    starts = np.flatnonzero(change).tolist()
    yield from zip(starts, [*starts[1:], n])


def _signatures(column: pa.ChunkedArray, hashes: int) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), "<u2").reshape(-1, hashes)


def _forest(sigs: np.ndarray, side: np.ndarray, cross: bool, rules) -> list[tuple[int, int]]:
    """Edges that span the graph of surviving pairs; in a pair of blocks, pairs across only."""
    edges, free = [], np.arange(len(sigs))
    while len(free):
        todo, free = [int(free[0])], free[1:]
        while todo and len(free):
            v = todo.pop()
            open_ = free[side[free] != side[v]] if cross else free
            hit = open_[survivors(sigs[v], sigs[open_], rules)] if len(open_) else open_
            if len(hit):
                edges += [(v, int(u)) for u in hit]
                todo += hit.tolist()
                free = np.setdiff1d(free, hit, assume_unique=True)
    return edges


def _bucket_edges(hashes: int, rules):
    keys = ["band", "bucket", "one", "two"]

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _runs(batches, keys):
            ids = table["class_id"].to_numpy()
            sigs = _signatures(table["signature"], hashes)
            side, one, two = table["side"].to_numpy(), table["one"].to_numpy(), table["two"].to_numpy()
            left, right = [], []
            for a, b in _groups(table, keys):
                if b - a < 2:
                    continue
                for u, v in _forest(sigs[a:b], side[a:b], bool(one[a] != two[a]), rules):
                    left.append(ids[a + u])
                    right.append(ids[a + v])
            left, right = np.asarray(left, np.int64), np.asarray(right, np.int64)
            pairs = np.unique(np.stack([np.minimum(left, right), np.maximum(left, right)], 1), axis=0) if len(left) else np.zeros((0, 2), np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], ["a", "b"])

    return run


def _deal(rows: DataFrame, group_keys: list[str], member: str, blocks: str) -> DataFrame:
    """Splits groups of many blocks: every row goes to each pair of blocks that has its own.

    Adds one <= two (the pair of blocks) and side (the row's own); a group of one block stays whole.
    """
    side = F.pmod(F.xxhash64(F.lit(3), member), F.col(blocks)).cast("int")
    pairs = F.transform(F.sequence(F.lit(0), F.col(blocks).cast("int") - 1), lambda o: F.struct(F.least(o, F.col("side")).alias("one"), F.greatest(o, F.col("side")).alias("two")))
    out = rows.withColumn("side", side).withColumn("pair", F.explode(pairs))
    out = out.withColumns({"one": F.col("pair.one"), "two": F.col("pair.two")}).drop("pair", blocks)
    return out.repartition(*group_keys, "one", "two").sortWithinPartitions(*group_keys, "one", "two")


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Connected components of an edge list: (id, root), root the least id; ids without edges are absent.

    Alternates large-star and small-star rounds on the edges (each a grouped
    minimum and a join), written to shared storage, until nothing changes.
    """
    now = materialise(edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct(), "edges")
    mark = now.agg(F.count(F.lit(1)), F.sum(F.hash("u", "v").cast("long"))).first()
    while mark[0]:
        both = now.unionAll(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct(F.col("u"), F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.u", "e.v")
        after = materialise(small.where("u <> v").distinct(), "edges")
        new_mark = after.agg(F.count(F.lit(1)), F.sum(F.hash("u", "v").cast("long"))).first()
        now = after
        if new_mark == mark:
            break
        mark = new_mark
    roots = now.select(F.col("v").alias("id")).distinct().join(now.select(F.col("u").alias("id")).distinct(), "id", "left_anti")
    return now.select(F.col("u").alias("id"), F.col("v").alias("root")).unionAll(roots.select("id", F.col("id").alias("root")))


def _shingle_rows(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    shingler = Shingler()
    for batch in batches:
        for at in range(0, batch.num_rows, 500):
            part = batch.slice(at, 500)
            sets = [shingler.shingles(t or "").tobytes() for t in part.column("text").to_pylist()]
            keep = [part.column(c) for c in ("class_id", "root", "blocks", "members", "signature")]
            yield pa.RecordBatch.from_arrays([*keep, pa.array(sets, pa.binary())], ["class_id", "root", "blocks", "members", "signature", "shingles"])


def _overlaps(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Bit rows over the shingles that stand in two sets or more, and the set sizes."""
    sizes = np.fromiter(map(len, sets), np.int64, len(sets))
    values, code, df = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    rank = np.cumsum(df > 1) - 1
    shared = int((df > 1).sum())
    bits = np.zeros((len(sets), shared // 64 + 1), np.uint64)
    row = np.repeat(np.arange(len(sets)), sizes)
    use = df[code] > 1
    place = rank[code[use]]
    np.bitwise_or.at(bits, (row[use], place // 64), np.uint64(1) << (place % 64).astype(np.uint64))
    return bits, sizes


def verify_block(sigs: np.ndarray, sets: list[np.ndarray], side: np.ndarray, members: np.ndarray, cross: bool, threshold: float = THRESHOLD, rules=None) -> tuple[np.ndarray, list[tuple[int, int]]]:
    """Links of each class in one pair of blocks (counting members of the partner) and edges that span them."""
    n = len(sets)
    links = np.zeros(n, np.int64)
    bits = sizes = None
    if n > 8:
        bits, sizes = _overlaps(sets)
    parent = list(range(n))

    def find(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    edges = []
    for i in range(n - 1):
        rest = np.arange(i + 1, n)
        if cross:
            rest = rest[side[rest] != side[i]]
        if len(rest):
            rest = rest[survivors(sigs[i], sigs[rest], rules)]
        if not len(rest):
            continue
        if bits is None:
            common = np.fromiter((len(np.intersect1d(sets[i], sets[j], assume_unique=True)) for j in rest), np.int64, len(rest))
            union = np.fromiter((len(sets[j]) for j in rest), np.int64, len(rest)) + len(sets[i]) - common
        else:
            common = np.bitwise_count(bits[rest] & bits[i]).sum(axis=1, dtype=np.int64)
            union = sizes[rest] + sizes[i] - common
        hit = rest[common >= threshold * union - 1e-9]
        if len(hit):
            links[i] += members[hit].sum()
            links[hit] += members[i]
            for j in hit.tolist():
                x, y = find(i), find(j)
                if x != y:
                    parent[max(x, y)] = min(x, y)
                    edges.append((i, j))
    return links, edges


def _verify(hashes: int, threshold: float, rules):
    keys = ["root", "one", "two"]

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _runs(batches, keys):
            ids, side = table["class_id"].to_numpy(), table["side"].to_numpy()
            members, one, two = table["members"].to_numpy(), table["one"].to_numpy(), table["two"].to_numpy()
            sigs = _signatures(table["signature"], hashes)
            blobs = table["shingles"]
            who: list = []
            links: list = []
            partner: list = []
            for a, b in _groups(table, keys):
                own, rows = np.unique(ids[a:b], return_index=True)  # a row that repeats its class's first one counts once
                rows = rows + a
                sets = [np.frombuffer(blobs[int(i)].as_py(), "<u8") for i in rows]
                found, edges = verify_block(sigs[rows], sets, side[rows], members[rows], bool(one[a] != two[a]), threshold, rules)
                hit = np.flatnonzero(found)
                who += own[hit].tolist() + [int(own[i]) for i, _ in edges]
                links += found[hit].tolist() + [0] * len(edges)
                partner += [None] * len(hit) + [int(own[j]) for _, j in edges]
            yield pa.RecordBatch.from_arrays([pa.array(who, pa.int64()), pa.array(links, pa.int64()), pa.array(partner, pa.int64())], ["class_id", "links", "partner"])

    return run


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """One row per input row: doc_id, class_id, n_links, kept, as near_groups() gives them."""
    return near_groups(docs, id_col, text_col, **options).select("doc_id", "class_id", "n_links", "kept")


def near_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD, hashes: int = HASHES, band_rows: int = BAND_ROWS, tolerance: float = TOLERANCE, bucket_block: int = BUCKET_BLOCK, block_classes: int = BLOCK_CLASSES, block_shingles: int = BLOCK_SHINGLES) -> DataFrame:
    """One row per input row: doc_id, text_key, class_id, n_links, kept, stays, copies.

    Two documents are linked when the Jaccard similarity of their sets of word
    n-grams is at least the threshold. n_links counts the other rows a document is
    linked to, copies included; class_id is the least id of its connected group and
    kept marks the row with that id. A null text is empty; a document without words
    has no n-grams, links to nothing and is kept in a class of its own. Rows with a
    null id stay, with a null class and no links. Rows that repeat an id and its text
    count as copies and share their decision; an id repeated with other texts keeps
    each text's own class. An empty table gives no rows.

    text_key is the xxhash64 of the text (a null one is empty). stays marks one id and
    text of each connected group, the least, and every row that is in no group; copies
    says whether further rows of the group may repeat that id and text.
    """
    spark = docs.sparkSession
    prepare(spark)
    rules = least_matches(hashes, STEP, threshold, tolerance)
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("text")).withColumn("text_key", F.xxhash64("text"))
    signed = materialise(slim.mapInArrow(freed(_sign(hashes)), "doc_id long, text_key long, set_key binary, n_shingles long, signature binary"), "signatures")
    sets = signed.where("set_key IS NOT NULL AND doc_id IS NOT NULL")
    grouped = sets.groupBy("set_key").agg(F.min(F.struct("doc_id", "text_key")).alias("first"), F.count(F.lit(1)).alias("members"), F.first("n_shingles").alias("n_shingles"), F.first("signature").alias("signature"))
    classes = materialise(grouped.select("set_key", F.col("first.doc_id").alias("class_id"), F.col("first.doc_id").alias("first_id"), F.col("first.text_key").alias("first_key"), "members", "n_shingles", "signature"), "classes")
    repeated = classes.groupBy("class_id").count().where("count > 1")
    if repeated.limit(1).count():  # an id repeated with other texts: further classes get numbers of their own
        place = F.row_number().over(Window.partitionBy("class_id").orderBy("set_key"))
        own = F.when(F.col("place") == 1, F.col("class_id")).otherwise(F.xxhash64("set_key").bitwiseOR(F.expr("shiftleft(1L, 63)")))
        classes = materialise(classes.withColumn("place", place).withColumn("class_id", own).drop("place"), "classes")
    width = 2 * band_rows
    bands = classes.select("class_id", F.posexplode(F.transform(F.sequence(F.lit(0), F.lit(hashes // band_rows - 1)), lambda i: F.xxhash64(F.substring(F.col("signature"), i * width + 1, F.lit(width))))).alias("band", "bucket"))
    full = bands.groupBy("band", "bucket").agg(F.count(F.lit(1)).alias("n")).where("n > 1").withColumn("blocks", F.ceil(F.col("n") / bucket_block)).drop("n")
    crowded = bands.join(full, ["band", "bucket"]).join(classes.select("class_id", "signature"), "class_id")
    dealt = _deal(crowded, ["band", "bucket"], "class_id", "blocks")
    candidate_edges = materialise(dealt.mapInArrow(freed(_bucket_edges(hashes, rules)), "a long, b long"), "candidate-edges")
    groups = materialise(components(candidate_edges), "candidate-groups").withColumnRenamed("id", "class_id")
    placed = groups.join(classes, "class_id")
    sizes = placed.groupBy("root").agg(F.greatest(F.ceil(F.count(F.lit(1)) / block_classes), F.ceil(F.sum("n_shingles") / block_shingles)).alias("blocks"))
    placed = materialise(placed.join(sizes, "root").select("class_id", "first_id", "first_key", "root", "blocks", "members", "signature"), "candidates")
    wanted = F.broadcast(placed) if placed.count() <= BROADCAST_ROWS else placed
    with_text = slim.join(wanted, (F.col("doc_id") == F.col("first_id")) & (F.col("text_key") == F.col("first_key")))
    shingled = with_text.select("class_id", "root", "blocks", "members", "signature", "text").mapInArrow(freed(_shingle_rows), "class_id long, root long, blocks long, members long, signature binary, shingles binary")
    verified = materialise(
        _deal(shingled, ["root"], "class_id", "blocks").mapInArrow(freed(_verify(hashes, threshold, rules)), "class_id long, links long, partner long"), "verified"
    )
    links = verified.groupBy("class_id").agg(F.sum("links").alias("links"))
    final = components(verified.where("partner IS NOT NULL").select(F.col("class_id").alias("a"), F.col("partner").alias("b"))).select(F.col("id").alias("class_id"), "root")
    rooted = classes.select("class_id", "first_id", "first_key", "set_key", "members").join(links, "class_id", "left").join(final, "class_id", "left").withColumn("root", F.coalesce("root", "class_id"))
    least = rooted.groupBy("root").agg(F.min(F.struct("first_id", "first_key")).alias("head"))
    named = rooted.join(least, "root").select("set_key", F.col("head.first_id").alias("root"), F.col("head.first_key").alias("head_key"), "members", (F.coalesce("links", F.lit(0)) + F.col("members") - 1).alias("n"))
    out = signed.join(named, "set_key", "left")
    class_id = F.coalesce("root", "doc_id")
    grouped_row = F.col("doc_id").isNotNull() & F.col("root").isNotNull()
    return out.select(
        "doc_id",
        "text_key",
        F.when(F.col("doc_id").isNotNull(), class_id).alias("class_id"),
        F.when(F.col("doc_id").isNull(), F.lit(0)).otherwise(F.coalesce("n", F.lit(0))).alias("n_links"),
        F.coalesce(F.col("doc_id") == class_id, F.lit(True)).alias("kept"),
        (~grouped_row | ((F.col("doc_id") == F.col("root")) & (F.col("text_key") == F.col("head_key")))).alias("stays"),
        (grouped_row & (F.col("members") > 1)).alias("copies"),
    )
