"""Iteration plumbing: shared storage between the turns of a driver loop."""

from __future__ import annotations

import os
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import Column, DataFrame, Observation, SparkSession

ROOT = str(Path(__file__).resolve().parents[2])


def prepare(spark: SparkSession) -> None:
    """Lets Python workers import this package where PYTHONPATH does not name it."""
    env = spark.sparkContext.environment
    known = os.environ.get("PYTHONPATH", "").split(os.pathsep) + env.get("PYTHONPATH", "").split(os.pathsep)
    if ROOT not in known:
        env["PYTHONPATH"] = os.pathsep.join(p for p in [ROOT, env.get("PYTHONPATH", "")] if p)


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where none is set, a temporary folder on one machine, and an error on a cluster."""
    sc = spark.sparkContext
    named = sc.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="treefold-"))
        named = sc.getCheckpointDir()
    return named.rstrip("/")


def _file_system(spark: SparkSession, path: str):
    jvm_path = spark._jvm.org.apache.hadoop.fs.Path(path)
    return jvm_path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), jvm_path


def scratch_folder(spark: SparkSession, name: str) -> str:
    """A fresh path in the shared folder, deleted when the session ends."""
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    files, jvm_path = _file_system(spark, path)
    files.deleteOnExit(jvm_path)
    return path


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Writes df to shared storage and reads it back, which cuts the lineage of a loop and survives lost executors."""
    spark = df.sparkSession
    path = scratch_folder(spark, name)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.scratch_path = path
    return out


def measured(df: DataFrame, name: str, **measures: Column) -> tuple[DataFrame, dict]:
    """materialise(), and aggregates of the rows that come from the same pass."""
    seen = Observation(name)
    out = materialise(df.observe(seen, *[m.alias(k) for k, m in measures.items()]), name)
    return out, seen.get


def release(*frames: DataFrame) -> None:
    """Deletes materialised tables that nothing reads any more."""
    for df in frames:
        path = getattr(df, "scratch_path", None)
        if path:
            files, jvm_path = _file_system(df.sparkSession, path)
            files.delete(jvm_path, True)
