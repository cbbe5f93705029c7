"""Small-state problems on chains that grow: one vector of states for each user, folded in event order."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.columns import cents
from ..operators.finite import Tables
from ..operators.problems import Problem
from ..plans.iterate import prepare


class ChainFold:
    """The newest event is the top: its vector is the vector so far, lifted over the edge, joined into it."""

    def __init__(self, problem: Problem):
        self.t = Tables(problem)
        self._no = np.zeros(1, bool)

    def step(self, value: list[int] | None, w: int) -> list[int]:
        weight = np.array([w], np.int64)
        own = self.t.start(self._no, weight, 1)
        if value is not None:
            below = np.array(value, np.int64).reshape(1, -1, 1)
            own = self.t.joined(own, self.t.lifted(below, self._no, self.pending))
        self.pending = weight
        return own[0, :, 0].tolist()

    pending = np.zeros(1, np.int64)

    def run(self, value: list[int] | None, last_w: int, weights: list[int]) -> tuple[list[int], int]:
        self.pending = np.array([last_w], np.int64)
        for w in weights:
            value = self.step(value, w)
            last_w = w
        return value, last_w

    def best(self, value: list[int]) -> int | None:
        return self.t.best(np.array(value, np.int64))


def _weights(events: DataFrame) -> DataFrame:
    return events.select("user_id", "ts", "event_id", cents(F.col("value")).alias("w"))


def batch_chain(events: DataFrame, problem: Problem) -> DataFrame:
    """(user_id, value) of the whole table: each user's events folded in order. Vertex-weighted problems only read w once."""
    prepare(events.sparkSession)

    def run(table: pa.Table) -> pa.Table:
        order = np.lexsort((table["event_id"].to_numpy(), table["ts"].to_numpy()))
        fold = ChainFold(problem)
        value, _ = fold.run(None, 0, table["w"].to_numpy()[order].tolist())
        return pa.table({"user_id": table["user_id"].slice(0, 1), "value": pa.array([fold.best(value)], pa.int64())})

    return _weights(events).groupBy("user_id").applyInArrow(run, "user_id long, value long")


def chain_dp(events: DataFrame, problem: Problem) -> DataFrame:
    """Streaming (user_id, n_events, value), updated with each micro-batch.

    events needs a watermark on ts. Rows wait in the state until the watermark has passed
    them, as the fold is sensitive to order; rows behind the watermark are dropped by Spark.
    """
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    prepare(events.sparkSession)

    def update(key, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        values, last_w, n, waiting = state.get if state.exists else ([], 0, 0, [])
        waiting = [tuple(x) for x in waiting]
        for b in batches:
            waiting += list(zip((b["us"]).tolist(), b["event_id"].tolist(), b["w"].tolist()))
        mark = state.getCurrentWatermarkMs() * 1000
        waiting.sort()
        due = [x for x in waiting if x[0] <= mark]
        rest = waiting[len(due) :]
        fold = ChainFold(problem)
        if due:
            value, last_w = fold.run(list(values) or None, last_w, [x[2] for x in due])
            values, n = value, n + len(due)
        state.update((list(values), int(last_w), int(n), [list(x) for x in rest]))
        if rest:
            state.setTimeoutTimestamp(max(int(rest[0][0] // 1000) + 1, state.getCurrentWatermarkMs() + 1))
        if values:
            yield pd.DataFrame({"user_id": [key[0]], "n_events": [n], "value": [fold.best(values)]})

    rows = events.select("user_id", "ts", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"), "event_id", cents(F.col("value")).alias("w"))
    return rows.groupBy("user_id").applyInPandasWithState(
        update, "user_id long, n_events long, value long", "vals array<long>, last_w long, n long, waiting array<array<long>>", "update", GroupStateTimeout.EventTimeTimeout
    )


def windowed_dp(events: DataFrame, problem: Problem, kind: str = "tumbling", size: str = "7 days", slide: str | None = None) -> DataFrame:
    """(user_id, start, value): the chain of each user and window. For batch tables and inside foreachBatch."""
    prepare(events.sparkSession)
    if kind == "session":
        gap = F.lag("ts").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
        marked = _weights(events).withColumn("opens", F.coalesce((F.col("ts") > gap + F.expr(f"INTERVAL {size}")).cast("long"), F.lit(1)))
        w = Window.partitionBy("user_id").orderBy("ts", "event_id")
        placed = marked.withColumn("no", F.sum("opens").over(w))
        starts = placed.groupBy("user_id", "no").agg(F.min("ts").alias("start"))
        rows = placed.join(starts, ["user_id", "no"]).select("user_id", "start", "ts", "event_id", "w")
    else:
        rows = _weights(events).withColumn("win", F.window("ts", size, slide or size)).select("user_id", F.col("win.start").alias("start"), "ts", "event_id", "w")

    def run(table: pa.Table) -> pa.Table:
        order = np.lexsort((table["event_id"].to_numpy(), table["ts"].to_numpy()))
        fold = ChainFold(problem)
        value, _ = fold.run(None, 0, table["w"].to_numpy()[order].tolist())
        return pa.table({"user_id": table["user_id"].slice(0, 1), "start": table["start"].slice(0, 1), "value": pa.array([fold.best(value)], pa.int64())})

    return rows.groupBy("user_id", "start").applyInArrow(run, f"user_id long, start {dict(rows.dtypes)['start']}, value long")


def join_static(events: DataFrame, customers: DataFrame) -> DataFrame:
    """Events with their customer's segment (stream-static)."""
    return events.join(customers.select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id", "left")


def dedup_events(events: DataFrame) -> DataFrame:
    """One row for each event id; a stream must have a watermark."""
    return events.dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


def purchases_after_views(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """(view_id, purchase_id) of one user's view and later purchase (stream-stream interval join)."""
    views = events.where("event_type = 'view'").select("user_id", F.col("event_id").alias("view_id"), F.col("ts").alias("view_ts"))
    buys = events.where("event_type = 'purchase'").select(F.col("user_id").alias("buyer"), F.col("event_id").alias("purchase_id"), F.col("ts").alias("buy_ts"))
    near = F.expr(f"buyer = user_id AND buy_ts >= view_ts AND buy_ts <= view_ts + INTERVAL {within}")
    return views.join(buys, near).select("view_id", "purchase_id")


def run_available(stream: DataFrame, folder: str) -> DataFrame:
    """Runs an appending stream over all that is there, into Parquet files in folder, and returns their rows."""
    out = f"{folder}/rows"
    query = stream.writeStream.format("parquet").outputMode("append").option("path", out).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(out)


def events_stream(spark: SparkSession, sf_dir: str, delay: str = "0 seconds") -> DataFrame:
    """The events table as a stream with a watermark."""
    path = f"{sf_dir}/events.parquet"
    source = spark.readStream.schema(spark.read.parquet(path).schema)
    jvm_path = spark._jvm.org.apache.hadoop.fs.Path(path)
    if not jvm_path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(jvm_path).isDirectory():
        # a stream reads folders: this one's other tables are left out by name
        source, path = source.option("pathGlobFilter", "events.parquet"), sf_dir
    return source.parquet(path).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)
