"""Token-id files: ORC stripes with integer run-length encoding, row indexes and Bloom filters.

Documents are range-partitioned by id, encoded and written as ORC; each file is
a run of ids in ascending order. Readers get whole stripes in parallel, and a
look-up by id is pruned by file statistics, row indexes and Bloom filters.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import prepare, scratch_path, text_or_empty
from .tokens import encoded_slices

ROW = "part int, doc_id long, local_start long, n_tokens long, ids array<int>"
ROW_INDEX_STRIDE = 1000
HEAD_CHARS = 32


def _encode(path: str | None):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, start = TaskContext.get().partitionId(), 0
        for (doc_ids,), encoded in encoded_slices(batches, path):
            sizes = np.fromiter(map(len, encoded), np.int64, len(encoded))
            ends = np.cumsum(sizes)
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], ends)), pa.int32()), pa.array(np.concatenate(encoded).astype(np.int32)))
            n = len(encoded)
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.full(n, part, np.int32)), pa.array(doc_ids, pa.int64()), pa.array(start + ends - sizes), pa.array(sizes), lists],
                ["part", "doc_id", "local_start", "n_tokens", "ids"],
            )
            start += int(ends[-1])

    return run


def write_token_files(docs: DataFrame, path: str, tokenizer_path: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Writes the ids of every document to ORC files under path, in ascending doc id (null ids first, equal ids by text).

    An id that many rows share, or the null id, is split over tasks by the head
    of the text, and equal rows by their place.
    """
    prepare(docs.sparkSession)
    text = text_or_empty(text_col)
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("text"), F.length(text).alias("chars"), F.monotonically_increasing_id().alias("place"))
    dealt = slim.repartitionByRange("doc_id", F.substring("text", 1, HEAD_CHARS), "place").sortWithinPartitions("doc_id", "text", "place")
    (
        dealt.mapInArrow(_encode(tokenizer_path), ROW)
        .write.option("orc.bloom.filter.columns", "doc_id")
        .option("orc.bloom.filter.fpp", "0.01")
        .option("orc.row.index.stride", str(ROW_INDEX_STRIDE))
        .option("compression", "zstd")
        .orc(path)
    )


def _digest(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        lists = batch.column("ids")
        values = np.ascontiguousarray(lists.values.to_numpy(), "<i4")
        offsets = lists.offsets.to_numpy()
        crc = [zlib.crc32(values[a:b].tobytes()) for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist())]
        yield pa.RecordBatch.from_arrays([batch.column("part"), batch.column("doc_id"), batch.column("local_start"), batch.column("n_tokens"), pa.array(crc, pa.int64())], ["part", "doc_id", "local_start", "n_tokens", "ids_crc32"])


def read_token_files(spark: SparkSession, path: str) -> DataFrame:
    """The files' rows: doc_id, start (ids of all documents before it), n_tokens, ids."""
    rows = spark.read.schema(ROW).orc(path)
    return rows.join(F.broadcast(_file_starts(rows)), "part").select("doc_id", (F.col("file_start") + F.col("local_start")).alias("start"), "n_tokens", "ids")


def _file_starts(rows: DataFrame) -> DataFrame:
    """Ids before each file: one row per file, from the n_tokens column alone."""
    totals = rows.groupBy("part").agg(F.sum("n_tokens").alias("total"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    return totals.select("part", F.coalesce(F.sum("total").over(before), F.lit(0)).alias("file_start"))


def digest_token_files(spark: SparkSession, path: str) -> DataFrame:
    """Per document, from the files: doc_id, start, n_tokens, ids_crc32 of its little-endian uint32 ids."""
    prepare(spark)
    rows = spark.read.schema(ROW).orc(path)
    starts = F.broadcast(_file_starts(rows))
    digests = rows.mapInArrow(_digest, "part int, doc_id long, local_start long, n_tokens long, ids_crc32 long")
    return digests.join(starts, "part").select("doc_id", (F.col("file_start") + F.col("local_start")).alias("start"), "n_tokens", "ids_crc32")


def lookup(spark: SparkSession, path: str, doc_ids: list[int]) -> DataFrame:
    """Rows of the given ids; the filter reaches the ORC reader, which prunes by statistics and Bloom filters."""
    return spark.read.schema(ROW).orc(path).where(F.col("doc_id").isin(doc_ids)).select("doc_id", "n_tokens", "ids")


def round_trip(docs: DataFrame, path: str | None = None, tokenizer_path: str | None = None) -> DataFrame:
    """Writes token files and returns their digests.

    A null text is empty and holds the end id alone; repeated rows are written
    each; an empty table gives no rows; other columns are ignored.
    """
    spark = docs.sparkSession
    path = path or scratch_path(spark, "tokens")
    write_token_files(docs, path, tokenizer_path)
    return digest_token_files(spark, path)
