"""Exact dedup with a cuckoo-filter index over live content digests.

Every task first folds its own rows into an index (so a digest that a third of
all rows share leaves a task once), then each digest partition merges the
partial entries into its index. A filter hit is never trusted: it is checked
against the digests stored in the same partition, and a digest that several
rows share is checked against their content, bucketed by digest. When the
filter overflows it is rebuilt twice as large from the stored keys.
"""

from __future__ import annotations

from array import array
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise, prepare, text_or_empty
from .fingerprints import in_bitmap, slot_bitmap

PARTITION_ROWS = 2_000_000
SLOTS = 4
MAX_KICKS = 200
_MIX = 0x9E3779B97F4A7C15
_MASK = (1 << 64) - 1


class CuckooFilter:
    """Partial-key cuckoo filter: 16-bit tags, two candidate buckets of four slots."""

    def __init__(self, capacity: int = 1024):
        buckets = 1
        while buckets * SLOTS * 0.9 < max(capacity, SLOTS):
            buckets *= 2
        self.mask = buckets - 1
        self.table = array("H", bytes(2 * buckets * SLOTS))
        self.size = 0
        self._turn = 0

    @staticmethod
    def tag(key: int) -> int:
        return (key >> 48) or 1

    def _other(self, bucket: int, tag: int) -> int:
        return (bucket ^ ((tag * _MIX & _MASK) >> 24)) & self.mask

    def _put(self, bucket: int, tag: int) -> bool:
        base = bucket * SLOTS
        for slot in range(base, base + SLOTS):
            if not self.table[slot]:
                self.table[slot] = tag
                return True
        return False

    def contains(self, key: int) -> bool:
        tag = self.tag(key)
        first = key & self.mask
        for bucket in (first, self._other(first, tag)):
            base = bucket * SLOTS
            if tag in self.table[base : base + SLOTS]:
                return True
        return False

    def insert(self, key: int) -> bool:
        """False when no place was found; the table is then as it was."""
        tag = self.tag(key)
        bucket = key & self.mask
        if self._put(bucket, tag) or self._put(self._other(bucket, tag), tag):
            self.size += 1
            return True
        undo = []
        for _ in range(MAX_KICKS):
            self._turn = (self._turn + 1) % SLOTS
            slot = bucket * SLOTS + self._turn
            undo.append((slot, self.table[slot]))
            tag, self.table[slot] = self.table[slot], tag
            bucket = self._other(bucket, tag)
            if self._put(bucket, tag):
                self.size += 1
                return True
        for slot, old in reversed(undo):
            self.table[slot] = old
        return False

    def delete(self, key: int) -> bool:
        """Removes one copy of a key that was inserted."""
        tag = self.tag(key)
        first = key & self.mask
        for bucket in (first, self._other(first, tag)):
            for slot in range(bucket * SLOTS, bucket * SLOTS + SLOTS):
                if self.table[slot] == tag:
                    self.table[slot] = 0
                    self.size -= 1
                    return True
        return False


class CuckooIndex:
    """Filter in front of the live content keys; key -> [largest doc id, rows]."""

    def __init__(self, capacity: int = 1024):
        self.filter = CuckooFilter(capacity)
        self.live: dict[bytes, list] = {}
        self.resizes = 0
        self.false_hits = 0

    @staticmethod
    def short(key: bytes) -> int:
        return int.from_bytes(key[:8], "little")

    def _insert(self, key: bytes) -> None:
        if self.filter.insert(self.short(key)):
            return
        size = max(1024, 2 * len(self.live))
        while True:
            self.resizes += 1
            bigger = CuckooFilter(size)
            if all(bigger.insert(self.short(k)) for k in self.live):
                self.filter = bigger
                return
            size *= 2

    def add(self, key: bytes, doc_id: int | None, rows: int = 1) -> bool:
        """True when the content was new."""
        if self.filter.contains(self.short(key)):
            entry = self.live.get(key)
            if entry is not None:
                entry[1] += rows
                if doc_id is not None and (entry[0] is None or doc_id > entry[0]):
                    entry[0] = doc_id
                return False
            self.false_hits += 1
        self.live[key] = [doc_id, rows]
        self._insert(key)
        return True

    def remove(self, key: bytes) -> bool:
        """Takes a digest out of the live set; False when it was not live."""
        if not self.filter.contains(self.short(key)) or key not in self.live:
            return False
        del self.live[key]
        return self.filter.delete(self.short(key))

    def drain(self) -> pa.RecordBatch:
        keys = list(self.live)
        values = list(self.live.values())
        return pa.RecordBatch.from_arrays(
            [pa.array(keys, pa.binary()), pa.array([v[0] for v in values], pa.int64()), pa.array([v[1] for v in values], pa.int64())],
            ["digest", "keep_id", "group_size"],
        )


def _feed(index: CuckooIndex, batch: pa.RecordBatch) -> None:
    columns = [batch.column(i).to_pylist() for i in range(batch.num_columns)]
    add = index.add
    for row in zip(*columns):
        add(*row)


def _fold(flush_at: int | None):
    """Folds (digest, doc id[, rows]) into an index; flush_at bounds what a combiner holds."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = CuckooIndex()
        for batch in batches:
            for at in range(0, batch.num_rows, 20_000):
                _feed(index, batch.slice(at, 20_000))
                if flush_at and len(index.live) >= flush_at:
                    yield index.drain()
                    index = CuckooIndex()
        if index.live:
            yield index.drain()

    return run


ENTRY = "digest binary, keep_id long, group_size long"


def index_digests(digests: DataFrame, combine_rows: int = 200_000, partitions: int | None = None) -> DataFrame:
    """(doc_id, digest) -> one row per live digest: digest, keep_id, group_size.

    partitions: None makes them of about PARTITION_ROWS rows of the input, so that
    what an index holds does not grow with the table.
    """
    spark = digests.sparkSession
    prepare(spark)
    if partitions is None:
        partitions = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-digests.count() // PARTITION_ROWS))
    partial = digests.select("digest", "doc_id").mapInArrow(_fold(combine_rows), ENTRY)
    return partial.repartition(partitions, "digest").mapInArrow(_fold(None), ENTRY)


def _unfold() -> Callable:
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = CuckooIndex()
        out: list[bytes] = []
        for batch in batches:
            for digest, live in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                if live:
                    index.add(digest, None)
                elif index.remove(digest):
                    out.append(digest)
        yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], ["digest"])

    return run


def delete_digests(entries: DataFrame, gone: DataFrame) -> DataFrame:
    """The live entries (digest, keep_id, group_size) without those of `gone` (a digest column, repeats and unknown ones do no harm).

    Both sides meet by digest; each partition inserts its live digests and takes the others out.
    """
    prepare(entries.sparkSession)
    rows = entries.select("digest", F.lit(True).alias("live")).unionAll(gone.select("digest", F.lit(False).alias("live")).distinct())
    removed = rows.repartition("digest").sortWithinPartitions(F.col("live").desc()).mapInArrow(_unfold(), "digest binary")
    return entries.join(removed, "digest", "left_anti").select("digest", "keep_id", "group_size")


def unlike_contents(docs: DataFrame, digests: Column, entries: DataFrame, text_col: str = "text") -> DataFrame:
    """Digests whose rows do not all hold the same text, from the content of all rows that share one.

    A bitmap of a fixed size keeps back texts whose digest surely stands alone, so
    little but copies moves.
    """
    shared = entries.where("group_size > 1").select("digest")
    short = F.xxhash64("digest")
    marks = slot_bitmap(shared.select(short.alias("h")), "shared-digests")
    rows = docs.select(digests.alias("digest"), text_or_empty(text_col).alias("text")).withColumn("__ed_marks", marks.scalar())
    rows = rows.where(in_bitmap(F.col("__ed_marks"), short)).drop("__ed_marks").join(shared, "digest", "left_semi")
    return rows.groupBy("digest").agg(F.min("text").alias("least"), F.max("text").alias("most")).where("least <> most").select("digest")


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256.

    Texts are equal when identical; a null text equals the empty text. The row
    with the largest id of a group stays. Null ids lose to any id; a group of
    null ids only keeps them. Rows that repeat an id and its text count as rows
    of the group and share its decision. An empty table gives an empty result;
    other columns are ignored. Equal digests are checked against the texts; two
    texts of one digest, which nobody has seen yet, raise an error.
    """
    digest = F.unhex(F.sha2(text_or_empty(text_col), 256))
    rows = materialise(docs.select(F.col(id_col).cast("long").alias("doc_id"), digest.alias("digest")), "digests")
    entries = materialise(index_digests(rows), "digest-index")
    if unlike_contents(docs, digest, entries, text_col).limit(1).count():
        raise RuntimeError("two texts share a SHA-256 digest")
    return rows.join(entries, "digest").select(
        "doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256")
    )
