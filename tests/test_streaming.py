import shutil

from pyspark.sql import functions as F

from treefold.operators.problems import PROBLEMS
from treefold.streaming import batch_chain, chain_dp, dedup_events, join_static, purchases_after_views, windowed_dp


def test_stream_equals_batch(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet").where("user_id < 4")  # ts without a zone; streams cast it
    src, out = tmp_path / "in", tmp_path / "out"
    marks = [r[0] for r in events.selectExpr("date_trunc('week', ts) AS d").distinct().orderBy("d").collect()]
    for i, d in enumerate(marks):
        events.where(F.date_trunc("week", "ts") == d).coalesce(1).write.parquet(str(tmp_path / f"part{i}"))
    src.mkdir()
    for i in range(len(marks)):
        for j, f in enumerate(sorted((tmp_path / f"part{i}").glob("*.parquet"))):
            shutil.copy(f, src / f"{i:03d}-{j}.parquet")
    # a last event far in the future lets the watermark pass all others
    last = events.agg(F.max("ts")).first()[0]
    tail = events.limit(1).withColumn("ts", F.lit(last) + F.expr("INTERVAL 400 DAYS")).withColumn("user_id", F.lit(999).cast("long"))
    tail.select(*events.columns).coalesce(1).write.parquet(str(tmp_path / "tail"))
    for f in (tmp_path / "tail").glob("*.parquet"):
        shutil.copy(f, src / "999.parquet")
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(src)).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 day")
    seen = {}

    def keep(batch, _):
        for r in batch.collect():
            seen[r["user_id"]] = (r["n_events"], r["value"])

    q = chain_dp(stream, PROBLEMS["mis"]()).writeStream.outputMode("update").foreachBatch(keep).option("checkpointLocation", str(out)).trigger(availableNow=True).start()
    q.awaitTermination()
    want = {r["user_id"]: r["value"] for r in batch_chain(events, PROBLEMS["mis"]()).collect()}
    counts = {r["user_id"]: r["count"] for r in events.groupBy("user_id").count().collect()}
    assert {u: seen[u] for u in want} == {u: (counts[u], v) for u, v in want.items()}


def test_windows(spark, sf):
    events = spark.read.parquet(f"{sf}/events.parquet").where("user_id < 3")
    whole = {r["user_id"]: r["value"] for r in batch_chain(events, PROBLEMS["subtree_size"]()).collect()}
    for kind, options in (("tumbling", {"size": "7 days"}), ("session", {"size": "12 hours"})):
        got = windowed_dp(events, PROBLEMS["subtree_size"](), kind, **options).groupBy("user_id").agg(F.sum("value").alias("n")).collect()
        assert {r["user_id"]: r["n"] for r in got} == whole, kind
    sliding = windowed_dp(events, PROBLEMS["subtree_size"](), "sliding", "2 days", "1 day").agg(F.sum("value")).first()[0]
    assert sliding == 2 * sum(whole.values())


def test_joins_and_dedup(spark, sf):
    events = spark.read.parquet(f"{sf}/events.parquet")
    customers = spark.read.parquet(f"{sf}/customer.parquet")
    assert join_static(events, customers).count() == events.count()
    assert dedup_events(events.unionAll(events)).count() == events.count()
    pairs = purchases_after_views(events, "1 day").count()
    assert pairs > 0
