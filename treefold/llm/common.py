"""Shared plumbing: shared scratch space, worker set-up, small column helpers."""

from __future__ import annotations

import ctypes
import gc
import os
import tempfile
import uuid
from collections.abc import Callable, Iterator
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

REPO_ROOT = str(Path(__file__).resolve().parents[2])
#: ASCII white space of the contracts: space and U+0009 to U+000D.
ASCII_SPACE = " \t\n\x0b\x0c\r"
NOT_SPACE = r"[^\x20\x09-\x0D]+"
MAX_LONG = 9223372036854775807


def prepare(spark: SparkSession) -> None:
    """Lets Python workers import this package when PYTHONPATH does not name it."""
    if REPO_ROOT not in os.environ.get("PYTHONPATH", "").split(os.pathsep):
        env = spark.sparkContext.environment
        paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
        if REPO_ROOT not in paths:
            env["PYTHONPATH"] = os.pathsep.join([REPO_ROOT, *paths])


def give_back() -> None:
    """Returns freed memory of a Python worker to the machine; workers wait between stages and would keep it."""
    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc has it, other C libraries do not
    if trim:
        trim(0)


def freed(run: Callable[..., Iterator]) -> Callable[..., Iterator]:
    """A function of mapInArrow that gives its memory back at the end of a task."""

    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return wrapped


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share (spark.checkpoint.dir).

    Only where the session names none, as in tests on one machine, is a
    temporary one made; on a cluster that is an error.
    """
    sc = spark.sparkContext
    named = sc.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="treefold-"))
        named = sc.getCheckpointDir()
    return named.rstrip("/")


def scratch_path(spark: SparkSession, name: str) -> str:
    """A fresh path in the shared folder, deleted when the session ends."""
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    jvm_path = spark._jvm.org.apache.hadoop.fs.Path(path)
    jvm_path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(jvm_path)
    return path


def release(spark: SparkSession, path: str) -> None:
    """Deletes a scratch path whose readers are done."""
    jvm_path = spark._jvm.org.apache.hadoop.fs.Path(path)
    jvm_path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(jvm_path, True)


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Writes df as Parquet to shared scratch and reads it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def fresh(df: DataFrame, name: str) -> str:
    """The name, lengthened until no column of df has it."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def text_or_empty(column: str = "text") -> Column:
    return F.coalesce(F.col(column), F.lit(""))


def word_count(column: Column) -> Column:
    """Maximal runs of anything but ASCII white space; null counts 0."""
    return F.coalesce(F.regexp_count(column, F.lit(NOT_SPACE)), F.lit(0)).cast("long")


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet")


def crc_fold(id_column: Column, modulus: int, remainder: int) -> Column:
    """True where crc32 of the id's decimal text leaves the remainder."""
    return F.pmod(F.crc32(id_column.cast("string").cast("binary")), F.lit(modulus)) == remainder


def labelled_sample(
    docs: DataFrame,
    marks: DataFrame,
    label: str,
    modulus: int,
    remainder: int,
    per_class: int,
    max_chars: int,
    id_col: str = "doc_id",
    text_col: str = "text",
    seed: int = 11,
) -> list[tuple[int, str, int]]:
    """At most per_class labelled rows of each class outside the held-out fold, and at most max_chars of text in all.

    A row whose text would pass max_chars is left out; later rows that fit still count.
    Rows come in the order of a seeded hash of their ids, so the sample is a fair
    one, the same in every run. These two bounds are what the driver may hold.
    """
    usable = marks.where(F.col(label).isin(0, 1) & F.col("doc_id").isNotNull() & ~crc_fold(F.col("doc_id"), modulus, remainder))
    once = usable.groupBy(F.col("doc_id").cast("long").alias("__s_id")).agg(F.min(label).alias("__s_label"))
    ordered = once.withColumn("__s_order", F.xxhash64(F.lit(seed), "__s_id"))
    picked = ordered.where("__s_label = 0").orderBy("__s_order").limit(per_class).unionAll(ordered.where("__s_label = 1").orderBy("__s_order").limit(per_class))
    slim = docs.select(F.col(id_col).cast("long").alias("__s_id"), text_or_empty(text_col).alias("__s_text"))
    # at most 2 * per_class rows, so the hint is safe at any size of the corpus
    found = slim.join(F.broadcast(picked), "__s_id").withColumn("__s_chars", F.length("__s_text"))
    total, kept = 0, set()
    for order, chars in sorted(tuple(r) for r in found.select("__s_order", "__s_chars").collect()):
        # a text that does not fit is left out, and the next one tried
        if total + chars <= max_chars:
            total += chars
            kept.add((order, chars))
    if not kept:
        return []
    fits = docs.sparkSession.createDataFrame(sorted(kept), "__s_order long, __s_chars long")
    rows = found.join(F.broadcast(fits), ["__s_order", "__s_chars"]).select("__s_id", "__s_text", "__s_label", "__s_order").distinct().orderBy("__s_order", "__s_text")
    return [(r[0], r[1], int(r[2])) for r in rows.collect()]
