"""Builders of the workload trees over the given tables: one function each, all in the TREE schema."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.columns import cents, knuth_parent

LEVEL = 1_000_000_000


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _tree(rows: DataFrame, tree_id: str = "0", parent: str = "parent", node: str = "node", node_w: str = "w", edge_w: str = "w", child_ord: str = "0") -> DataFrame:
    return rows.selectExpr(
        f"cast({tree_id} as bigint) AS tree_id",
        f"cast({node} as bigint) AS node_id",
        f"cast({parent} as bigint) AS parent_id",
        f"cast({child_ord} as int) AS child_ord",
        f"cast({node_w} as bigint) AS node_w",
        f"CASE WHEN {parent} IS NULL THEN NULL ELSE cast({edge_w} as bigint) END AS edge_w",
    )


def _line_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with a dense rank over all columns as id.

    Ranks are dense over the whole table, so that every engine numbers alike; they come from
    the counts of smaller orders plus the rank inside the order, not from one global window.
    """
    lines = load(spark, sf_dir, "lineitem")
    rest = [c for c in lines.columns if c != "l_orderkey"]
    inside = F.row_number().over(Window.partitionBy("l_orderkey").orderBy(*rest))
    counts = lines.groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n"))
    span = counts.withColumn("bucket", F.floor(F.col("l_orderkey") / 10_000))
    before_bucket = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    buckets = span.groupBy("bucket").agg(F.sum("n").alias("bn")).select("bucket", F.coalesce(F.sum("bn").over(before_bucket), F.lit(0)).alias("bucket_from"))
    before = Window.partitionBy("bucket").orderBy("l_orderkey").rowsBetween(Window.unboundedPreceding, -1)
    starts = span.withColumn("inside_from", F.coalesce(F.sum("n").over(before), F.lit(0))).join(buckets, "bucket").select("l_orderkey", (F.col("bucket_from") + F.col("inside_from")).alias("start"))
    numbered = lines.select("l_orderkey", "l_extendedprice", inside.alias("rn"))
    return numbered.join(starts, "l_orderkey").select("l_orderkey", (F.col("start") + F.col("rn")).alias("rank"), cents(F.col("l_extendedprice")).alias("w"))


def catalog(spark: SparkSession, sf_dir: str) -> DataFrame:
    """all -> region -> nation -> customer -> orders -> lineitem; depth 5, moderate fan-out."""
    root = spark.range(1).selectExpr("0L AS node", "cast(NULL AS bigint) AS parent", "1L AS w")
    regions = load(spark, sf_dir, "region").selectExpr(f"{LEVEL} + r_regionkey AS node", "0L AS parent", "1L AS w")
    nations = load(spark, sf_dir, "nation").selectExpr(f"{2 * LEVEL}L + n_nationkey AS node", f"cast({LEVEL} + n_regionkey AS bigint) AS parent", "1L AS w")
    customers = load(spark, sf_dir, "customer").select((F.col("c_custkey") + 3 * LEVEL).alias("node"), (F.col("c_nationkey").cast("long") + 2 * LEVEL).alias("parent"), cents(F.abs("c_acctbal")).alias("w"))
    orders = load(spark, sf_dir, "orders").select((F.col("o_orderkey") + 4 * LEVEL).alias("node"), (F.col("o_custkey") + 3 * LEVEL).alias("parent"), cents(F.col("o_totalprice")).alias("w"))
    lines = _line_ids(spark, sf_dir).select((F.col("rank") + 5 * LEVEL).alias("node"), (F.col("l_orderkey") + 4 * LEVEL).alias("parent"), "w")
    return _tree(root.unionAll(regions).unionAll(nations).unionAll(customers).unionAll(orders).unionAll(lines))


def customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The catalog cut at customer level: a tree of orders and lines for each customer."""
    roots = load(spark, sf_dir, "customer").select(F.col("c_custkey").alias("tree"), (F.col("c_custkey") + 3 * LEVEL).alias("node"), F.lit(None).cast("long").alias("parent"), cents(F.abs("c_acctbal")).alias("w"))
    owners = load(spark, sf_dir, "orders").select(F.col("o_custkey").alias("tree"), F.col("o_orderkey"), cents(F.col("o_totalprice")).alias("w"))
    orders = owners.select("tree", (F.col("o_orderkey") + 4 * LEVEL).alias("node"), (F.col("tree") + 3 * LEVEL).alias("parent"), "w")
    lines = _line_ids(spark, sf_dir).join(owners.select("tree", F.col("o_orderkey").alias("l_orderkey")), "l_orderkey").select("tree", (F.col("rank") + 5 * LEVEL).alias("node"), (F.col("l_orderkey") + 4 * LEVEL).alias("parent"), "w")
    return _tree(roots.unionAll(orders).unionAll(lines), tree_id="tree")


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").select("event_id", "user_id", "ts", cents(F.col("value")).alias("w"))


def chain_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All events in time order, one path."""
    return _tree(_events(spark, sf_dir).selectExpr("event_id AS node", "CASE WHEN event_id > 0 THEN event_id - 1 END AS parent", "w"))


def chain_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A path for each user."""
    before = F.lag("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return _tree(_events(spark, sf_dir).withColumn("parent", before).withColumnRenamed("event_id", "node"), tree_id="user_id")


def heap(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The complete binary tree over events."""
    return _tree(_events(spark, sf_dir).selectExpr("event_id AS node", "CASE WHEN event_id > 0 THEN (event_id + 1) div 2 - 1 END AS parent", "w"))


def heap_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("node"), cents(F.col("o_totalprice")).alias("w"))
    return _tree(rows.selectExpr("node", "CASE WHEN node > 0 THEN (node + 1) div 2 - 1 END AS parent", "w"))


def random(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every event hangs below a scattered earlier one."""
    return _tree(_events(spark, sf_dir).select(F.col("event_id").alias("node"), F.when(F.col("event_id") > 0, knuth_parent(F.greatest("event_id", F.lit(1)))).alias("parent"), "w"))


def star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All parts under one root."""
    parts = load(spark, sf_dir, "part").select((F.col("p_partkey") + 1).alias("node"), F.lit(0).cast("long").alias("parent"), cents(F.col("p_retailprice")).alias("w"))
    return _tree(spark.range(1).selectExpr("0L AS node", "cast(NULL AS bigint) AS parent", "0L AS w").unionAll(parts))


def broom(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The chain of all events with all lines fanned out at its end."""
    last = load(spark, sf_dir, "events").agg(F.max("event_id").alias("parent"))
    lines = _line_ids(spark, sf_dir).select((F.col("rank") + 5 * LEVEL).alias("node"), "w").withColumn("parent", last.scalar())
    return chain_all(spark, sf_dir).unionAll(_tree(lines.select("node", "parent", "w")))


def caterpillar(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Even events are the spine, odd ones its leaves."""
    rule = "CASE WHEN event_id = 0 THEN NULL WHEN event_id % 2 = 0 THEN event_id - 2 ELSE event_id - 1 END AS parent"
    return _tree(_events(spark, sf_dir).selectExpr("event_id AS node", rule, "w"))


def threads(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turns of each conversation, weighted by their length."""
    rows = load(spark, sf_dir, "conversations").selectExpr("conv_id", "turn", "conv_id * 1000 + turn AS node", "cast(length(text) AS bigint) AS w")
    before = F.lag("node").over(Window.partitionBy("conv_id").orderBy("turn"))
    return _tree(rows.withColumn("parent", before), tree_id="conv_id", edge_w="1", child_ord="0")


def site(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Suffixes of host labels -> host -> first path part -> page, from page addresses."""
    pages = load(spark, sf_dir, "pages").select("page_id", F.coalesce(F.parse_url("url", F.lit("HOST")), F.lit("")).alias("host"), F.coalesce(F.split(F.parse_url("url", F.lit("PATH")), "/")[1], F.lit("")).alias("part"), F.length("html").cast("long").alias("w"))
    labels = F.reverse(F.split("host", r"\."))
    prefixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, 1, i), "."))
    full = F.array_join(labels, ".")
    paths = pages.select("page_id", "w", F.concat(F.array(F.lit("")), prefixes, F.array(F.concat(full, F.lit("/"), F.col("part")))).alias("steps"))
    edges = paths.select(F.explode(F.transform(F.sequence(F.lit(1), F.size("steps")), lambda i: F.struct(F.get("steps", i - 1).alias("name"), F.when(i > 1, F.get("steps", i - 2)).alias("above")))).alias("s")).select("s.*").distinct()
    ids = edges.select("name").distinct().withColumn("id", F.row_number().over(Window.orderBy("name")).cast("long"))
    above = ids.select(F.col("name").alias("above"), F.col("id").alias("parent"))
    inner = edges.join(ids, "name").join(above, "above", "left").selectExpr("id AS node", "parent", "1L AS w")
    leaf_parent = paths.select("page_id", "w", F.element_at("steps", -1).alias("name")).join(ids, "name").selectExpr(f"{LEVEL} + page_id AS node", "id AS parent", "w")
    return _tree(inner.unionAll(leaf_parent))


def corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Root -> language -> (language, source) -> document; documents weigh their characters."""
    docs = load(spark, sf_dir, "documents").select("doc_id", F.coalesce("lang", F.lit("")).alias("lang"), F.coalesce("source", F.lit("")).alias("source"), F.coalesce("n_chars", F.lit(0)).alias("w"))
    langs = docs.select("lang").distinct().withColumn("lid", F.dense_rank().over(Window.orderBy("lang")).cast("long"))
    pairs = docs.select("lang", "source").distinct().withColumn("pid", F.dense_rank().over(Window.orderBy("lang", "source")).cast("long"))
    root = spark.range(1).selectExpr("0L AS node", "cast(NULL AS bigint) AS parent", "0L AS w")
    l_rows = langs.selectExpr(f"{LEVEL} + lid AS node", "0L AS parent", "0L AS w")
    p_rows = pairs.join(langs, "lang").selectExpr(f"{2 * LEVEL}L + pid AS node", f"{LEVEL} + lid AS parent", "0L AS w")
    d_rows = docs.join(F.broadcast(pairs), ["lang", "source"]).selectExpr(f"{3 * LEVEL}L + doc_id AS node", f"{2 * LEVEL}L + pid AS parent", "w")
    return _tree(root.unionAll(l_rows).unionAll(p_rows).unionAll(d_rows))


def mst(spark: SparkSession, sf_dir: str, limit: int | None = None) -> DataFrame:
    """The minimum spanning tree of the embeddings by squared distance (see plans.spanning)."""
    from ..plans.spanning import spanning_tree

    rows = load(spark, sf_dir, "embeddings")
    return spanning_tree(rows.where(F.col("vec_id") < limit) if limit else rows)


BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "catalog": catalog,
    "customers": customers,
    "chain_all": chain_all,
    "chain_user": chain_user,
    "heap": heap,
    "heap_orders": heap_orders,
    "random": random,
    "star": star,
    "broom": broom,
    "caterpillar": caterpillar,
    "threads": threads,
    "site": site,
    "corpus": corpus,
    "mst": mst,
}


def tree(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    return BUILDERS[kind](spark, sf_dir)
