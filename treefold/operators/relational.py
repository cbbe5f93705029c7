"""Relational operators around the methods, each as a DataFrame plan and as the SQL it must equal."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.columns import cents, tagged
from ..sources.trees import load

Q = Callable[[SparkSession, str], DataFrame]
OPS: dict[str, tuple[Q, str | None]] = {}


def _op(sql: str | None):
    def add(f: Q) -> Q:
        OPS[f.__name__] = (f, sql)
        return f

    return add


CENTS = "cast(round({} * 100) AS BIGINT)"


@_op("SELECT o_orderkey AS node_id, o_custkey AS parent_id FROM orders")
def op_node_projection(spark, d):
    return load(spark, d, "orders").select(F.col("o_orderkey").alias("node_id"), F.col("o_custkey").alias("parent_id"))


@_op(f"SELECT o_orderkey, {CENTS.format('o_totalprice')} AS w FROM orders")
def op_cents_weights(spark, d):
    return load(spark, d, "orders").select("o_orderkey", cents(F.col("o_totalprice")).alias("w"))


@_op("SELECT p_partkey, p_partkey * 4 + 1 AS helper_id FROM part")
def op_node_id_tagging(spark, d):
    return load(spark, d, "part").select("p_partkey", tagged(F.col("p_partkey"), 1).alias("helper_id"))


@_op("SELECT o_orderkey FROM orders WHERE o_totalprice > 200000")
def op_leaf_filter(spark, d):
    return load(spark, d, "orders").where(F.col("o_totalprice") > 200000).select("o_orderkey")


@_op("SELECT c_custkey, c_acctbal FROM customer WHERE c_acctbal BETWEEN 0 AND 5000")
def op_weight_between(spark, d):
    return load(spark, d, "customer").where(F.col("c_acctbal").between(0, 5000)).select("c_custkey", "c_acctbal")


@_op("SELECT n_nationkey, n_name FROM nation WHERE n_regionkey IN (1, 3)")
def op_in_list(spark, d):
    return load(spark, d, "nation").where(F.col("n_regionkey").isin(1, 3)).select("n_nationkey", "n_name")


@_op("SELECT page_id FROM pages WHERE url LIKE '%e%'")
def op_like_url(spark, d):
    return load(spark, d, "pages").where(F.col("url").like("%e%")).select("page_id")


@_op("SELECT event_id FROM (SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events) WHERE p IS NULL")
def op_null_root(spark, d):
    before = F.lag("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return load(spark, d, "events").select("event_id", before.alias("p")).where("p IS NULL").select("event_id")


@_op("SELECT l_orderkey, count(*) AS n, min(o_custkey) AS parent_id FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY l_orderkey")
def op_parent_join(spark, d):
    joined = load(spark, d, "lineitem").select("l_orderkey").join(load(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    return joined.groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n"), F.min("o_custkey").alias("parent_id"))


_CATALOG_SQL = "SELECT n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name"


@_op(_CATALOG_SQL)
def op_catalog_broadcast(spark, d):
    # nation is a fixed table of 25 rows
    return load(spark, d, "customer").join(F.broadcast(load(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("customers"))


@_op("SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey")
def op_catalog_merge_hint(spark, d):
    return load(spark, d, "orders").join(load(spark, d, "customer").hint("merge"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_mktsegment")


@_op("SELECT o_orderkey, c_nationkey FROM orders JOIN customer ON o_custkey = c_custkey")
def op_shuffle_hash_hint(spark, d):
    return load(spark, d, "orders").join(load(spark, d, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_nationkey")


@_op("SELECT c_custkey AS node_id, count(o_orderkey) AS degree FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY c_custkey")
def op_degrees_with_zero(spark, d):
    counted = load(spark, d, "orders").groupBy(F.col("o_custkey").alias("node_id")).agg(F.count(F.lit(1)).alias("degree"))
    return load(spark, d, "customer").select(F.col("c_custkey").alias("node_id")).join(counted, "node_id", "left").select("node_id", F.coalesce("degree", F.lit(0)).alias("degree"))


@_op("SELECT c_custkey, s_suppkey FROM (SELECT * FROM customer WHERE c_custkey < 50) c FULL JOIN (SELECT * FROM supplier WHERE s_suppkey >= 20) s ON c_custkey = s_suppkey")
def op_full_children(spark, d):
    c, s = load(spark, d, "customer").where("c_custkey < 50"), load(spark, d, "supplier").where("s_suppkey >= 20")
    return c.join(s, F.col("c_custkey") == F.col("s_suppkey"), "full").select("c_custkey", "s_suppkey")


@_op("SELECT c_custkey, s_suppkey FROM customer FULL JOIN supplier ON c_custkey = s_suppkey")
def op_full_children_all(spark, d):
    return load(spark, d, "customer").join(load(spark, d, "supplier"), F.col("c_custkey") == F.col("s_suppkey"), "full").select("c_custkey", "s_suppkey")


@_op("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def op_internal_nodes(spark, d):
    return load(spark, d, "customer").join(load(spark, d, "orders"), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("c_custkey")


@_op("SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def op_leaves(spark, d):
    return load(spark, d, "orders").join(load(spark, d, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey"), "left_anti").select("o_orderkey")


@_op("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
def op_customers_without_orders(spark, d):
    return load(spark, d, "customer").join(load(spark, d, "orders"), F.col("o_custkey") == F.col("c_custkey"), "left_anti").select("c_custkey")


@_op("SELECT a.r_name AS one, b.r_name AS two FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey")
def op_region_pair_theta(spark, d):
    r = load(spark, d, "region")
    return r.alias("a").join(r.alias("b"), F.col("a.r_regionkey") < F.col("b.r_regionkey")).select(F.col("a.r_name").alias("one"), F.col("b.r_name").alias("two"))


@_op("SELECT i.b AS block_one, j.b AS block_two FROM (SELECT DISTINCT event_id % 6 AS b FROM events) i, (SELECT DISTINCT event_id % 4 AS b FROM events) j")
def op_cross_blocks(spark, d):
    """All pairs of the blocks that events are dealt to on two sides."""
    ids = load(spark, d, "events").select("event_id")
    blocks = lambda n, name: ids.select((F.col("event_id") % n).alias(name)).distinct()
    return blocks(6, "block_one").crossJoin(blocks(4, "block_two"))


@_op(
    """SELECT a.event_id AS error_id, b.event_id AS event_id FROM events a JOIN events b
       ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 DAY WHERE a.event_type = (SELECT min(event_type) FROM events)"""
)
def op_events_in_window_of_error(spark, d):
    """Range join on a bucketed equality: each left row looks into its own day and the next."""
    e = load(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    day = F.floor(F.unix_timestamp("ts") / 86400)
    first = e.agg(F.min("event_type")).scalar()
    left = e.where(F.col("event_type") == first).select(F.col("event_id").alias("error_id"), "user_id", F.col("ts").alias("from_ts"), F.explode(F.array(day, day + 1)).alias("bucket"))
    right = e.select("event_id", "user_id", "ts", day.alias("bucket"))
    near = (F.col("ts") > F.col("from_ts")) & (F.col("ts") <= F.col("from_ts") + F.expr("INTERVAL 1 DAY"))
    return left.join(right, ["user_id", "bucket"]).where(near).select("error_id", "event_id")


@_op(
    f"""WITH RECURSIVE t AS (SELECT event_id AS id, CASE WHEN event_id > 0 THEN (event_id + 1) // 2 - 1 END AS p FROM events WHERE event_id < 255),
        anc AS (SELECT id, p AS a FROM t WHERE p IS NOT NULL UNION ALL SELECT anc.id, t.p FROM anc JOIN t ON t.id = anc.a WHERE t.p IS NOT NULL)
        SELECT a AS ancestor, count(*) AS below FROM anc GROUP BY a"""
)
def op_nested_interval_ancestor(spark, d):
    """Ancestors by containment of intervals: a heap vertex's subtree on the lowest level is a range of places."""
    v = load(spark, d, "events").where("event_id < 255").select((F.col("event_id") + 1).alias("h"))
    level = F.floor(F.log2("h")).cast("int")
    low = F.expr("shiftleft(h, 7 - cast(floor(log2(h)) as int))")
    v = v.select((F.col("h") - 1).alias("id"), level.alias("level"), low.alias("low"), F.expr("shiftleft(h + 1, 7 - cast(floor(log2(h)) as int)) - 1").alias("high"))
    inner, outer = v.alias("i"), v.alias("o")
    inside = (F.col("i.low") >= F.col("o.low")) & (F.col("i.high") <= F.col("o.high")) & (F.col("i.level") > F.col("o.level"))
    return outer.join(inner, inside).groupBy(F.col("o.id").alias("ancestor")).agg(F.count(F.lit(1)).alias("below"))


@_op(
    """WITH RECURSIVE t AS (SELECT event_id AS id, CASE WHEN event_id > 0 THEN (event_id + 1) // 2 - 1 END AS p FROM events),
        anc AS (SELECT id, p AS a FROM t WHERE p IS NOT NULL UNION ALL SELECT anc.id, t.p FROM anc JOIN t ON t.id = anc.a WHERE t.p IS NOT NULL)
        SELECT a AS ancestor, count(*) AS below FROM anc GROUP BY a"""
)
def op_heap_ancestors_all(spark, d):
    """Ancestors in the heap of all events: a vertex's are its place (from 1) shifted right, so nothing is joined."""
    place = load(spark, d, "events").select((F.col("event_id") + 1).alias("h")).where("h > 1")
    # bin() has as many digits as the place has levels above and with it
    shifts = F.sequence(F.lit(1), F.length(F.bin("h")) - 1)
    above = place.select(F.explode(F.transform(shifts, lambda i: F.call_function("shiftright", F.col("h"), i) - 1)).alias("ancestor"))
    return above.groupBy("ancestor").agg(F.count(F.lit(1)).alias("below"))


@_op(
    """SELECT event_id, last_value(v IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS view_id
       FROM (SELECT *, CASE WHEN event_type = 'view' THEN event_id END AS v FROM events) QUALIFY event_type = 'purchase'"""
)
def op_last_view_before_purchase(spark, d):
    """As-of join of two event kinds: one pass over each user's events instead of a range join."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    e = load(spark, d, "events").withColumn("view_id", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w))
    return e.where("event_type = 'purchase'").select("event_id", "view_id")


@_op("SELECT o_orderkey, n_regionkey FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey")
def op_grandparent(spark, d):
    c = load(spark, d, "customer").join(load(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    return load(spark, d, "orders").join(c, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "n_regionkey")


@_op("SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 2")
def op_lateral_children_topk(spark, d):
    w = Window.partitionBy("o_custkey").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    return load(spark, d, "orders").withColumn("rn", F.row_number().over(w)).where("rn <= 2").select("o_custkey", "o_orderkey")


@_op("SELECT l_orderkey AS parent_id, count(*) AS degree FROM lineitem GROUP BY l_orderkey")
def op_degree_count(spark, d):
    return load(spark, d, "lineitem").groupBy(F.col("l_orderkey").alias("parent_id")).agg(F.count(F.lit(1)).alias("degree"))


@_op(f"SELECT c_nationkey, sum({CENTS.format('c_acctbal')})::BIGINT AS total, count(*) AS n FROM customer GROUP BY c_nationkey")
def op_subtree_level_sums(spark, d):
    return load(spark, d, "customer").groupBy("c_nationkey").agg(F.sum(cents(F.col("c_acctbal"))).alias("total"), F.count(F.lit(1)).alias("n"))


@_op("SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS children FROM nation GROUP BY n_regionkey")
def op_children_list(spark, d):
    return load(spark, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_list("n_name")), ",").alias("children"))


@_op("SELECT l_orderkey, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_orderkey")
def op_distinct_fanout(spark, d):
    return load(spark, d, "lineitem").groupBy("l_orderkey").agg(F.count_distinct("l_partkey").alias("parts"))


@_op("SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem")
def op_dedup_nodes(spark, d):
    return load(spark, d, "lineitem").select("l_orderkey", "l_suppkey").dropDuplicates()


@_op("SELECT r_name, n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def op_rollup_region_nation(spark, d):
    n = load(spark, d, "nation").join(load(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return load(spark, d, "customer").join(n, F.col("c_nationkey") == F.col("n_nationkey")).rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("customers"))


@_op("SELECT c_mktsegment, o_orderstatus, count(*) AS orders FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY CUBE (c_mktsegment, o_orderstatus)")
def op_cube_segment_status(spark, d):
    return load(spark, d, "orders").join(load(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).cube("c_mktsegment", "o_orderstatus").agg(F.count(F.lit(1)).alias("orders"))


@_op("SELECT o_orderstatus, year(o_orderdate) AS y, count(*) AS n, grouping(o_orderstatus) AS g FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (year(o_orderdate)))")
def op_grouping_sets_order(spark, d):
    rows = load(spark, d, "orders").select("o_orderstatus", F.year("o_orderdate").alias("y"))
    return rows.groupingSets([["o_orderstatus"], ["y"]], "o_orderstatus", "y").agg(F.count(F.lit(1)).alias("n"), F.grouping("o_orderstatus").cast("long").alias("g"))


@_op("SELECT user_id, count(*) FILTER (event_type = 'view') AS views, count(*) FILTER (event_type = 'purchase') AS purchases FROM events GROUP BY user_id")
def op_pivot_event_type(spark, d):
    p = load(spark, d, "events").groupBy("user_id").pivot("event_type", ["view", "purchase"]).agg(F.count(F.lit(1)))
    return p.select("user_id", F.coalesce("view", F.lit(0)).alias("views"), F.coalesce("purchase", F.lit(0)).alias("purchases"))


@_op(None)
def op_approx_distinct_parents(spark, d):
    return load(spark, d, "orders").agg(F.approx_count_distinct("o_custkey").alias("parents"))


@_op(None)
def op_percentile_weights(spark, d):
    return load(spark, d, "orders").agg(F.percentile_approx("o_totalprice", [0.25, 0.5, 0.75]).alias("quartiles"))


@_op("SELECT n_nationkey, row_number() OVER (PARTITION BY n_regionkey ORDER BY n_nationkey) AS child_ord FROM nation")
def op_child_rank(spark, d):
    return load(spark, d, "nation").select("n_nationkey", F.row_number().over(Window.partitionBy("n_regionkey").orderBy("n_nationkey")).cast("long").alias("child_ord"))


@_op("SELECT o_orderkey, rank() OVER w AS r, dense_rank() OVER w AS dr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate)")
def op_rank_dense(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate")
    return load(spark, d, "orders").select("o_orderkey", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("dr"))


@_op("SELECT event_id, ntile(4) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS piece FROM events")
def op_ntile_pieces(spark, d):
    return load(spark, d, "events").select("event_id", F.ntile(4).over(Window.partitionBy("user_id").orderBy("ts", "event_id")).cast("long").alias("piece"))


@_op("SELECT o_orderkey, round(percent_rank() OVER (PARTITION BY o_custkey ORDER BY o_totalprice), 6) AS pr FROM orders")
def op_percent_rank(spark, d):
    return load(spark, d, "orders").select("o_orderkey", F.round(F.percent_rank().over(Window.partitionBy("o_custkey").orderBy("o_totalprice")), 6).alias("pr"))


@_op("SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS parent_id FROM events")
def op_user_chain(spark, d):
    return load(spark, d, "events").select("event_id", F.lag("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("parent_id"))


@_op("SELECT event_id, epoch_us(lead(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) - epoch_us(ts) AS gap_us FROM events")
def op_lead_gap(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    return load(spark, d, "events").select("event_id", (F.lead(us).over(w) - us).alias("gap_us"))


@_op(f"SELECT event_id, sum({CENTS.format('value')}) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW)::BIGINT AS s FROM events")
def op_running_sum_rows(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-3, 0)
    return load(spark, d, "events").select("event_id", F.sum(cents(F.col("value"))).over(w).alias("s"))


@_op("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM (SELECT *, date_trunc('second', ts) AS ts2 FROM events) e(event_id, ts0, user_id, event_type, value, props, ts)")
def op_range_frame_1day(spark, d):
    w = Window.partitionBy("user_id").orderBy("sec").rangeBetween(-86400, 0)
    e = load(spark, d, "events").withColumn("sec", F.unix_timestamp(F.date_trunc("second", "ts")))
    return e.select("event_id", F.count(F.lit(1)).over(w).alias("n"))


@_op(f"SELECT user_id, first_value(event_id) OVER w AS first_id, last_value(event_id) OVER w AS last_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) = 1")
def op_first_last(spark, d):
    e = load(spark, d, "events").groupBy("user_id")
    return e.agg(F.min_by("event_id", F.struct("ts", "event_id")).alias("first_id"), F.max_by("event_id", F.struct("ts", "event_id")).alias("last_id"))


@_op("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def op_topk_heavy_edges(spark, d):
    return load(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(25)


@_op("SELECT l_orderkey, l_extendedprice FROM lineitem QUALIFY row_number() OVER (PARTITION BY l_orderkey ORDER BY l_extendedprice DESC) = 1")
def op_topk_per_parent(spark, d):
    # the largest of each parent needs no window: a partial maximum leaves each task once
    return load(spark, d, "lineitem").groupBy("l_orderkey").agg(F.max("l_extendedprice").alias("l_extendedprice"))


@_op("SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events ORDER BY p NULLS FIRST, event_id LIMIT 20")
def op_sort_nulls(spark, d):
    p = F.lag("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return load(spark, d, "events").select("event_id", p.alias("p")).orderBy(F.col("p").asc_nulls_first(), "event_id").limit(20)


@_op("SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events ORDER BY p NULLS FIRST, event_id")
def op_sort_nulls_all(spark, d):
    p = F.lag("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return load(spark, d, "events").select("event_id", p.alias("p")).orderBy(F.col("p").asc_nulls_first(), "event_id")


@_op("SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
def op_union_levels(spark, d):
    return load(spark, d, "customer").select(F.col("c_nationkey").alias("k")).union(load(spark, d, "supplier").select("s_nationkey")).distinct()


@_op("SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def op_intersect_parents(spark, d):
    return load(spark, d, "customer").select(F.col("c_nationkey").alias("k")).intersect(load(spark, d, "supplier").select(F.col("s_nationkey").alias("k")))


@_op("SELECT o_orderkey AS k FROM orders EXCEPT SELECT l_orderkey FROM lineitem")
def op_except_leaves(spark, d):
    return load(spark, d, "orders").select(F.col("o_orderkey").alias("k")).subtract(load(spark, d, "lineitem").select(F.col("l_orderkey").alias("k")))


@_op("SELECT r_regionkey::BIGINT AS id, r_name AS name FROM region UNION ALL SELECT n_nationkey, n_name FROM nation")
def op_union_all_by_name(spark, d):
    r = load(spark, d, "region").select(F.col("r_regionkey").cast("long").alias("id"), F.col("r_name").alias("name"))
    return r.unionByName(load(spark, d, "nation").select(F.col("n_name").alias("name"), F.col("n_nationkey").cast("long").alias("id")))


@_op("SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
def op_above_avg_siblings(spark, d):
    load(spark, d, "orders").createOrReplaceTempView("tf_orders")
    return spark.sql("SELECT o_orderkey FROM tf_orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM tf_orders i WHERE i.o_custkey = o.o_custkey)")


@_op("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def op_exists_order(spark, d):
    return load(spark, d, "customer").join(load(spark, d, "orders").where("o_totalprice > 300000"), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("c_custkey")


@_op(None)
def op_sample_edges(spark, d):
    """A seeded hash sample: the same rows in every run."""
    return load(spark, d, "orders").where(F.pmod(F.xxhash64("o_orderkey", F.lit(1)), F.lit(10)) == 0).select("o_orderkey")


@_op("SELECT event_id, json_extract_string(props, '$.' || json_keys(props)[1]) AS first_prop FROM events WHERE props IS NOT NULL")
def op_json_props(spark, d):
    e = load(spark, d, "events").where("props IS NOT NULL").select("event_id", F.from_json("props", "map<string,string>").alias("m"))
    return e.select("event_id", F.get(F.map_values("m"), 0).alias("first_prop"))


@_op("SELECT date_trunc('day', ts)::TIMESTAMP AS day, count(*) AS n FROM events GROUP BY 1")
def op_day_counts(spark, d):
    return load(spark, d, "events").groupBy(F.date_trunc("day", "ts").cast("timestamp_ntz").alias("day")).agg(F.count(F.lit(1)).alias("n"))
