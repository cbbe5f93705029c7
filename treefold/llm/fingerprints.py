"""I-Match document fingerprints, in DataFrame operations only.

A first pass counts in how many distinct texts each term stands. The lexicon keeps
the terms inside a band of inverse document frequency, so neither words that
all documents share nor words of one document decide. A document's distinct
lexicon terms are sorted, and hashed once for each of several randomised
subsets of the lexicon. Subsets come in four densities, so that short and very
long documents alike have some that hold just a few of their terms: two texts
that share most terms then agree on many subset hashes.

The lexicon is held as a bitmap over term-hash slots, whose size is fixed, so
it can be sent to every task whatever the corpus; a term that shares the slot
of a lexicon term counts as one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise, text_or_empty

SLOT_BITS = 22
#: (first hash bit, bits) of each density; a density of b bits keeps 16 of 2**b parts of the lexicon.
DENSITIES = ((22, 4), (26, 6), (32, 8), (40, 10))
PARTS = 16
MIN_SHARE = 0.0005
MAX_SHARE = 0.25
_NOT_TERM = r"[^\p{L}\p{N}]+"


def distinct_terms(text: Column) -> Column:
    """Hashes of the distinct lower-cased runs of letters and digits."""
    return F.transform(F.array_distinct(F.array_remove(F.split(F.lower(text), _NOT_TERM), "")), lambda w: F.xxhash64(w))


def slot_bitmap(hashes: DataFrame, name: str) -> DataFrame:
    """One row, one column `bits`: the slots of all hashes in column h."""
    slot = F.col("h").bitwiseAND(F.lit((1 << SLOT_BITS) - 1))
    words = (
        hashes.select(F.shiftright(slot, 6).alias("at"), slot.bitwiseAND(F.lit(63)).alias("bit"))
        .groupBy("at")
        .agg(F.bit_or(F.expr("shiftleft(1L, cast(bit as int))")).alias("bits"))
    )
    every = hashes.sparkSession.range(1 << (SLOT_BITS - 6)).select(F.col("id").alias("at"))
    filled = every.join(words, "at", "left").select("at", F.coalesce("bits", F.lit(0).cast("long")).alias("bits"))
    return materialise(filled.agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "bits"))), lambda x: x["bits"]).alias("bits")), name)


def in_bitmap(bits: Column, h: Column) -> Column:
    word = F.get(bits, F.shiftright(h.bitwiseAND(F.lit((1 << SLOT_BITS) - 1)), 6).cast("int"))
    return F.getbit(word, h.bitwiseAND(F.lit(63)).cast("int")) == 1


def lexicon_bitmap(docs: DataFrame, text_col: str = "text", min_share: float = MIN_SHARE, max_share: float = MAX_SHARE) -> DataFrame:
    """One row, one column `bits`: the slots of all terms that stand in at least 2 and min_share..max_share of all distinct texts.

    Exact copies count as one text, so a text that many rows hold keeps its terms.
    Only rows whose key may be a repeated one (a bitmap tells) are grouped by key;
    all others are counted where they lie.
    """
    text = text_or_empty(text_col)
    keyed = docs.select(text.alias("text"), F.xxhash64(text).alias("h"), F.xxhash64(F.lit(1), text).alias("h_two"))
    copies = materialise(keyed.groupBy("h", "h_two").agg(F.count(F.lit(1)).alias("n")), "text-copies")
    total = copies.count()
    low, high = max(2, int(min_share * total)), max(2, int(max_share * total))
    marked = keyed.withColumn("fp_copied", slot_bitmap(copies.where("n > 1"), "copied-texts").scalar())
    copied = in_bitmap(F.col("fp_copied"), F.col("h"))
    once = marked.where(~copied).select("text").unionAll(marked.where(copied).groupBy("h", "h_two").agg(F.first("text").alias("text")).select("text"))
    counted = once.select(F.explode(distinct_terms(F.col("text"))).alias("h")).groupBy("h").agg(F.count(F.lit(1)).alias("df"))
    return slot_bitmap(counted.where(F.col("df").between(low, high)), "lexicon")


def _short(value: Column) -> Column:
    """A hash as a non-zero int; 0 stands for an empty subset."""
    low = value.bitwiseAND(F.lit(0x7FFFFFFF)).cast("int")
    return F.when(low == 0, F.lit(1)).otherwise(low)


def _level(sorted_terms: Column, first: int, width: int) -> Column:
    """The hashes of one density's subsets."""

    def part_of(h):
        return F.shiftright(h, first).bitwiseAND(F.lit((1 << width) - 1))

    def parts(chosen):
        def one(j):
            mine = F.filter(chosen, lambda h: part_of(h) == j)
            return F.when(F.size(mine) == 0, F.lit(0)).otherwise(_short(F.xxhash64(mine)))

        return F.transform(F.sequence(F.lit(0).cast("long"), F.lit(PARTS - 1).cast("long")), one)

    return F.flatten(F.transform(F.array(F.filter(sorted_terms, lambda h: part_of(h) < PARTS)), parts))


def subset_hashes(text: Column, bits: Column) -> Column:
    """65 ints: one for each lexicon subset (0: no term in it), last the whole lexicon's (all terms', then the text's, where it has none)."""

    def of_terms(terms, raw):
        kept = F.filter(terms, lambda h: in_bitmap(bits, h))

        def of_lexicon(sorted_terms):
            whole = F.when(F.size(sorted_terms) > 0, _short(F.xxhash64(sorted_terms))).otherwise(_short(F.xxhash64(F.array_sort(terms), raw)))
            return F.concat(*[_level(sorted_terms, first, width) for first, width in DENSITIES], F.array(whole))

        return F.flatten(F.transform(F.array(F.array_sort(kept)), of_lexicon))

    return F.flatten(F.transform(F.array(distinct_terms(text)), lambda terms: of_terms(terms, text)))


def as_text(hashes: Column) -> Column:
    return F.array_join(F.transform(hashes, lambda h: F.lpad(F.lower(F.hex(h.cast("long"))), 8, "0")), "")


def likeness(a: Column, b: Column) -> Column:
    """Share of equal hashes among the subsets that hold a term of either text; 1 for equal fingerprints, 0 to 1."""
    pairs = F.filter(F.zip_with(a, b, lambda x, y: F.when((x == 0) & (y == 0), F.lit(-1)).otherwise((x == y).cast("int"))), lambda v: v >= 0)
    same = F.aggregate(pairs, F.lit(0), lambda s, v: s + v)
    return same / F.size(pairs)


def fingerprints(docs: DataFrame, text_col: str = "text", lexicon: DataFrame | None = None) -> DataFrame:
    """docs with column `subset_hashes` added (replaced if there): equal texts, equal hashes; null text is empty."""
    bits = lexicon if lexicon is not None else lexicon_bitmap(docs, text_col)
    return _with_hashes(docs, "subset_hashes", text_or_empty(text_col), bits)


def _with_hashes(rows: DataFrame, name: str, text: Column, lexicon: DataFrame) -> DataFrame:
    """The bitmap comes in as a scalar subquery: evaluated once, then a constant of the tasks.

    It is named first because subqueries may not stand inside lambdas; the two
    projections collapse into one as it is referred to once.
    """
    return rows.withColumn("fp_bits", lexicon.scalar()).withColumn(name, subset_hashes(text, F.col("fp_bits"))).drop("fp_bits")


class IdBuckets:
    """A bucket number that rises with the id: coarse quantiles, each cut evenly into finer ranges beyond `most`."""

    def __init__(self, ids: DataFrame, rows_each: int, most: int):
        total = ids.count()
        wanted = max(1, -(-total // rows_each))
        coarse = min(wanted, most)
        self.fine = -(-wanted // coarse)
        cuts = ids.agg(F.percentile_approx("fp_id", [i / coarse for i in range(coarse + 1)], 20 * most)).first()[0] if total else None
        self.edges = sorted(set(cuts or []))

    def column(self) -> Column:
        if len(self.edges) < 2:
            return F.lit(0).cast("long")
        longs = lambda values: F.expr(f"array({', '.join(f'{v}L' for v in values)})")
        inner = self.edges[1:-1]
        at = F.size(F.filter(longs(inner), lambda e: e < F.col("fp_id"))) if inner else F.lit(0)
        low, high = F.get(longs(self.edges[:-1]), at).cast("double"), F.get(longs(self.edges[1:]), at).cast("double")
        share = (F.col("fp_id").cast("double") - low) / F.greatest(high - low, F.lit(1.0))
        step = F.greatest(F.lit(0), F.least(F.lit(self.fine - 1), F.floor(share * self.fine)))
        return (at * self.fine + step).cast("long")


def edited_likeness(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bucket_rows: int = 2000, most_buckets: int = 200) -> DataFrame:
    """Fingerprints of every text and of its edited text, and their likeness.

    The edited text has the last third of its code points replaced by as many
    from the start of the next document by falling id (after the last, the
    first). Returns doc_id, n_chars, edited_sha256, fingerprint,
    edited_fingerprint, near_edited, near_next. A null text is empty; null ids
    come last; rows that repeat an id follow each other by their texts' hash. A
    single document is its own next. Empty tables give no rows.

    Each text moves once, into buckets of ids that are ordered on their own; the
    few rows at a bucket's end find their next document by a join on buckets.
    """
    text = text_or_empty(text_col)
    lexicon = lexicon_bitmap(docs, text_col)
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(id_col).cast("long"), F.expr("-9223372036854775807L")).alias("fp_id"), text.alias("text"))
    ids = materialise(slim.select("fp_id", F.xxhash64("text").alias("fp_tie")), "fingerprint-ids")
    bucket = IdBuckets(ids, bucket_rows, most_buckets).column().alias("fp_bucket")
    heads = materialise(ids.select("fp_id", "fp_tie", bucket).groupBy("fp_bucket").agg(F.max(F.struct("fp_id", "fp_tie")).alias("head")), "fingerprint-heads")
    # the next lower bucket that has rows; after the lowest, the highest
    falling = Window.orderBy(F.col("fp_bucket").desc())
    first = heads.agg(F.max("head").alias("top")).scalar()
    follow = heads.select("fp_bucket", F.coalesce(F.lead("head").over(falling), first).alias("follow"))
    follow = follow.select("fp_bucket", F.col("follow.fp_id").alias("fp_id"), F.col("follow.fp_tie").alias("fp_tie"))
    printed = fingerprints(slim, "text", lexicon)
    next_heads = (
        slim.withColumn("fp_tie", F.xxhash64("text"))
        .join(follow, ["fp_id", "fp_tie"])
        .groupBy("fp_bucket")
        .agg(F.first("text").alias("head_text"))
    )
    next_heads = fingerprints(next_heads, "head_text", lexicon).withColumnRenamed("subset_hashes", "head_hashes")
    order = Window.partitionBy("fp_bucket").orderBy(F.col("fp_id").desc(), F.col("fp_tie").desc())
    rows = printed.withColumns({"fp_tie": F.xxhash64("text")}).select("*", bucket)
    rows = rows.select("doc_id", "fp_bucket", "text", "subset_hashes", F.lead(F.struct("text", "subset_hashes")).over(order).alias("next"))
    joined = rows.join(next_heads, "fp_bucket", "left")
    next_text = F.when(F.col("next").isNull(), F.col("head_text")).otherwise(F.col("next.text"))
    next_hashes = F.when(F.col("next").isNull(), F.col("head_hashes")).otherwise(F.col("next.subset_hashes"))
    n = F.char_length("text")
    third = F.floor(n / F.lit(3)).cast("int")
    edited = F.concat(F.substring(F.col("text"), F.lit(1), n - third), F.substring(next_text, F.lit(1), third))
    made = joined.select("doc_id", n.cast("long").alias("n_chars"), edited.alias("edited"), "subset_hashes", next_hashes.alias("next_hashes"))
    made = _with_hashes(made, "edited_hashes", F.col("edited"), lexicon)
    return made.select(
        "doc_id",
        "n_chars",
        F.sha2("edited", 256).alias("edited_sha256"),
        as_text(F.col("subset_hashes")).alias("fingerprint"),
        as_text(F.col("edited_hashes")).alias("edited_fingerprint"),
        likeness(F.col("subset_hashes"), F.col("edited_hashes")).alias("near_edited"),
        likeness(F.col("subset_hashes"), F.col("next_hashes")).alias("near_next"),
    )
