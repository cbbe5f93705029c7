"""Parent lists from files, rooting of edge lists, and sinks."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import TREE
from ..plans.iterate import materialise

FORMATS = ("parquet", "orc", "json", "csv", "text")


def read_tree(spark: SparkSession, path: str, format: str = "parquet", schema: str = TREE, **options) -> DataFrame:
    """A parent list with an explicit schema; text files hold tab-separated fields in its order."""
    if format not in FORMATS:
        raise ValueError(f"format must be one of {FORMATS}")
    if format == "text":
        rows = spark.read.text(path)
        fields = F.split("value", "\t")
        names = [f.strip().split(" ") for f in schema.split(",")]
        return rows.select(*[F.when(fields[i] != "", fields[i]).cast(kind).alias(name) for i, (name, kind) in enumerate(names)])
    reader = spark.read.schema(schema).options(**options)
    return reader.option("header", "true").csv(path) if format == "csv" else reader.format(format).load(path)


def write(df: DataFrame, path: str, format: str = "parquet", partition_by: list[str] | None = None, bucket_by: tuple[int, str] | None = None, table: str | None = None, mode: str = "error") -> None:
    """Files at path, or a bucketed table (bucket_by=(n, column)) stored there so that later joins on the column move nothing."""
    writer = df.write.mode(mode).format(format)
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    if bucket_by:
        writer.bucketBy(*bucket_by).sortBy(bucket_by[1]).option("path", path).saveAsTable(table)
    else:
        writer.save(path)


def root_edges(edges: DataFrame, root: int, method: str = "bfs", max_rounds: int = 10_000) -> DataFrame:
    """Roots an undirected tree given as (a, b, w): (node_id, parent_id, edge_w).

    'bfs' takes a round for each level, for shallow trees. 'euler' orders the tour of
    directed edges, ranks it by pointer doubling (log rounds for any depth), and
    reads from the ranks which direction of each edge comes first.
    """
    both = edges.select("a", "b", "w").unionAll(edges.select(F.col("b").alias("a"), F.col("a").alias("b"), "w"))
    both = materialise(both, "edges")
    spark = edges.sparkSession
    if method == "bfs":
        done = spark.createDataFrame([(root, None, None)], "node_id long, parent_id long, edge_w long")
        frontier = done
        for _ in range(max_rounds):
            step = both.join(frontier.select(F.col("node_id").alias("a"), F.col("parent_id").alias("above")), "a")
            frontier = materialise(step.where(~F.col("b").eqNullSafe(F.col("above"))).select(F.col("b").alias("node_id"), F.col("a").alias("parent_id"), F.col("w").alias("edge_w")), "frontier")
            if not frontier.limit(1).count():
                return done
            done = materialise(done.unionAll(frontier), "rooted")
        raise ValueError("the graph is deeper than max_rounds or not a tree")
    # successor of (u, v) in the tour: the neighbour of v that follows u in v's cyclic order
    lists = both.groupBy("a").agg(F.array_sort(F.collect_list("b")).alias("around"))
    nxt = both.select(F.col("a").alias("u"), F.col("b").alias("v")).join(lists.withColumnRenamed("a", "v"), "v")
    place = F.array_position("around", F.col("u"))
    nxt = nxt.select("u", "v", F.col("v").alias("nu"), F.element_at("around", (F.pmod(place, F.size("around")) + 1).cast("int")).alias("nv"), F.element_at("around", 1).alias("first"))
    # the tour starts at the root's first neighbour; the edge before it is the end
    end = (F.col("nu") == root) & (F.col("nv") == F.col("first"))
    ptr = materialise(nxt.select("u", "v", F.when(~end, F.col("nu")).alias("nu"), F.when(~end, F.col("nv")).alias("nv"), F.when(end, 0).otherwise(1).cast("long").alias("dist")), "tour")
    for _ in range(math.ceil(math.log2(max(2, ptr.count()))) + 1):
        far = ptr.select(F.col("u").alias("nu"), F.col("v").alias("nv"), F.col("nu").alias("nnu"), F.col("nv").alias("nnv"), F.col("dist").alias("more"))
        ptr = materialise(ptr.join(far, ["nu", "nv"], "left").select("u", "v", F.col("nnu").alias("nu"), F.col("nnv").alias("nv"), (F.col("dist") + F.coalesce("more", F.lit(0))).alias("dist")), "tour")
    back = ptr.select(F.col("v").alias("u"), F.col("u").alias("v"), F.col("dist").alias("back"))
    down = ptr.join(back, ["u", "v"]).where(F.col("dist") > F.col("back"))
    rows = down.join(both.select(F.col("a").alias("u"), F.col("b").alias("v"), "w"), ["u", "v"]).select(F.col("v").alias("node_id"), F.col("u").alias("parent_id"), F.col("w").alias("edge_w"))
    return spark.createDataFrame([(root, None, None)], "node_id long, parent_id long, edge_w long").unionAll(rows)
