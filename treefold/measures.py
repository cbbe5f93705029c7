"""Cost measures and invariants, as DataFrames or driver numbers."""

from __future__ import annotations

import math
import re

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .model import METRICS
from .plans.decompose import Decomposition
from .plans.hashing import PolyHash
from .plans.iterate import materialise


def metrics_frame(spark: SparkSession, run_id: str, stage: str, rows: list[tuple[int, str, float]]) -> DataFrame:
    return spark.createDataFrame([(run_id, stage, int(t), k, float(v)) for t, k, v in rows], METRICS)


# ---- load balancing ----


def machine_load(df: DataFrame, h: PolyHash, weight: str = "w", key: str = "node_id") -> DataFrame:
    """(machine, load) of every machine that got something."""
    return df.groupBy(h.column(F.col(key)).alias("machine")).agg(F.sum(weight).alias("load"))


def maximum_load(df: DataFrame, h: PolyHash, weight: str = "w", key: str = "node_id") -> int:
    return machine_load(df, h, weight, key).agg(F.coalesce(F.max("load"), F.lit(0))).first()[0]


def load_bound_probability(n: int, delta: float) -> float:
    """Bound on the chance that the load of one weight group exceeds t = delta log n times its share."""
    t = delta * math.log2(max(2, n))
    return min(1.0, (math.e * 2 ** (1 / delta) / t) ** t)


def grouped_load_bound(df: DataFrame, weight: str, m: int) -> DataFrame:
    """One row, one column bound: weights in ascending order, m at a time, sum of the groups' largest.

    Ranks come from counts of equal weights, so one row for each distinct weight is ordered, not every row.
    """
    counts = df.groupBy(F.col(weight).alias("w")).agg(F.count(F.lit(1)).alias("c"))
    upto = Window.orderBy("w").rowsBetween(Window.unboundedPreceding, 0)
    spans = counts.withColumn("last", F.sum("c").over(upto)).withColumn("first", F.col("last") - F.col("c") + 1)
    # a group ends at ranks m, 2m, ... and at n: the weight there is the group's largest
    ends = F.floor(F.col("last") / m) - F.floor((F.col("first") - 1) / m)
    total = spans.agg(F.sum(F.col("w") * ends).alias("full"), F.max("last").alias("n"), F.max("w").alias("top")).first()
    extra = total["top"] if total["n"] and total["n"] % m else 0
    return df.sparkSession.createDataFrame([((total["full"] or 0) + (extra or 0),)], "bound long")


def hash_uniformity(df: DataFrame, h: PolyHash, key: str = "node_id") -> DataFrame:
    """(machines, keys, chi_square): near `machines` for a fair hash."""
    counts = df.groupBy(h.column(F.col(key)).alias("machine")).agg(F.count(F.lit(1)).alias("c"))
    stats = counts.agg(F.sum("c").alias("n"), F.sum(F.col("c") * F.col("c")).alias("sq"))
    return stats.select(F.lit(h.m).alias("machines"), F.col("n").alias("keys"), (F.col("sq") * F.lit(h.m) / F.col("n") - F.col("n")).alias("chi_square"))


def pairwise_collisions(h: PolyHash, keys: int = 2000) -> float:
    """Share of key pairs that meet, times the number of machines: near 1 for a 2-universal family."""
    import numpy as np

    at = np.bincount(h.evaluate(np.arange(keys)), minlength=h.m)
    return float((at * (at - 1)).sum() / (keys * (keys - 1)) * h.m)


# ---- trees and their binary extension ----


def degree_sum(tree: DataFrame) -> DataFrame:
    """(vertices, trees, degree_sum): counted over both ends the sum is 2 (n - trees)."""
    edges = F.sum(F.col("parent_id").isNotNull().cast("long"))
    return tree.agg(F.count(F.lit(1)).alias("vertices"), F.sum(F.col("parent_id").isNull().cast("long")).alias("trees"), (2 * edges).alias("degree_sum"))


def max_children(rows: DataFrame, parent: str = "parent_id") -> int:
    return rows.where(F.col(parent).isNotNull()).groupBy("tree_id", parent).count().agg(F.coalesce(F.max("count"), F.lit(0))).first()[0]


def original_parents(bt: DataFrame) -> DataFrame:
    """(tree_id, node_id, parent_id) after contracting helpers, in untagged ids: the original tree again."""
    helpers = bt.where("is_aux").select("tree_id", F.col("node_id").alias("parent_id"), F.col("origin_id").alias("up"))
    rows = bt.where("NOT is_aux").select("tree_id", "node_id", "parent_id").join(helpers, ["tree_id", "parent_id"], "left")
    return rows.select("tree_id", F.shiftright("node_id", 2).alias("node_id"), F.shiftright(F.coalesce("up", "parent_id"), 2).alias("parent_id"))


def check_binary_extension(tree: DataFrame, bt: DataFrame) -> dict[str, bool]:
    n, size = tree.count(), bt.count()
    back = original_parents(bt)
    want = tree.select("tree_id", "node_id", "parent_id")
    lost = want.exceptAll(back).limit(1).count() + back.exceptAll(want).limit(1).count()
    # a helper's origin must be reached by going up through helpers only
    up = bt.where("is_aux").select("tree_id", "node_id", "parent_id", "origin_id")
    above = bt.select("tree_id", F.col("node_id").alias("parent_id"), F.col("is_aux").alias("above_aux"), F.col("origin_id").alias("above_origin"))
    wrong = up.join(above, ["tree_id", "parent_id"], "left").where("NOT coalesce((above_aux AND above_origin = origin_id) OR (NOT above_aux AND parent_id = origin_id), false)").limit(1).count()
    return {"unique": bt.select("tree_id", "node_id").distinct().count() == size, "binary": max_children(bt) <= 2, "linear_size": size <= 3 * max(1, n), "round_trip": lost == 0, "origins": wrong == 0}


def blow_up(tree: DataFrame, bt: DataFrame) -> float:
    return bt.count() / max(1, tree.count())


# ---- decomposition ----


def check_connected(bt: DataFrame, assign: DataFrame) -> int:
    """Pieces that are not connected: a connected one has exactly one vertex whose parent is outside."""
    placed = bt.select("tree_id", "node_id", "parent_id").join(assign, ["tree_id", "node_id"])
    above = assign.select("tree_id", F.col("node_id").alias("parent_id"), F.col("comp_id").alias("up"))
    tops = placed.join(above, ["tree_id", "parent_id"], "left").groupBy("tree_id", "comp_id").agg(F.sum((~F.col("up").eqNullSafe(F.col("comp_id"))).cast("int")).alias("tops"))
    return tops.where("tops <> 1").count()


def leaf_identity(rows: DataFrame, node: str, parent: str) -> int:
    """Trees in which leaves are not the two-child vertices plus one."""
    kids = rows.where(F.col(parent).isNotNull()).groupBy("tree_id", F.col(parent).alias(node)).agg(F.count(F.lit(1)).alias("k"))
    both = rows.select("tree_id", node).join(kids, ["tree_id", node], "left").withColumn("k", F.coalesce("k", F.lit(0)))
    sums = both.groupBy("tree_id").agg(F.sum((F.col("k") == 0).cast("int")).alias("k0"), F.sum((F.col("k") == 2).cast("int")).alias("k2"))
    return sums.where("k0 <> k2 + 1").count()


def piece_measures(dec: Decomposition) -> dict[str, float]:
    row = dec.comp.agg(F.count(F.lit(1)), F.max("n_vertices"), F.max("n_children")).first()
    logs = {k: dec.measure(k) for k in ("selected_share", "longest_walk", "merged")}
    share = dec.n / max(1, dec.m)
    return {
        "components": float(row[0]),
        "iterations": float(dec.iterations),
        "max_piece_over_share": (row[1] or 0) / max(1.0, share),
        "max_children": float(row[2] or 0),
        "selected_share": max([0.0, *logs["selected_share"]]),
        "longest_walk": max([0.0, *logs["longest_walk"]]),
        "total_merged": sum(logs["merged"]),
    }


def check_decomposition(bt: DataFrame, dec: Decomposition, stop_factor: int = 14) -> dict[str, bool]:
    sums = dec.assign.groupBy("tree_id", "node_id").count()
    covered = sums.count() == dec.n and sums.where("count > 1").limit(1).count() == 0
    pieces = dec.comp.count()
    size = dec.comp.agg(F.max("n_vertices")).first()[0] or 0
    slack = 4 * math.log2(max(2, dec.n)) + 1
    return {
        "covers": covered,
        "connected": check_connected(bt, dec.assign) == 0,
        "few_pieces": pieces <= stop_factor * dec.m + dec.trees,
        "binary": max_children(dec.comp, "parent_comp") <= 2,
        "bounded_pieces": size <= max(1.0, dec.n / dec.m) * slack,
    }


# ---- rounds, space, data sent, operations ----


def exchanges(df: DataFrame) -> int:
    """Exchange nodes of a plan: communication rounds of one action."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return len(re.findall(r"\bExchange\b|BroadcastExchange", text))


def decomposition_rounds(dec: Decomposition) -> DataFrame:
    """(turn, components, longest_walk, rounds): rounds are the communication steps of each turn of the loop.

    Counting children, sums and new parents are one each, walks take log2 of the longest, rounded up.
    """
    by_turn: dict[int, dict[str, float]] = {}
    for turn, name, value in dec.metrics:
        by_turn.setdefault(turn, {})[name] = value
    rows = []
    for turn, v in sorted(by_turn.items()):
        if "components" in v:
            walk = int(v.get("longest_walk", 0))
            rows.append((turn, int(v["components"]), walk, 3 + math.ceil(math.log2(1 + walk))))
    return dec.comp.sparkSession.createDataFrame(rows, "turn int, components long, longest_walk long, rounds int")


def row_bytes(df: DataFrame) -> Column:
    """Bytes of a row's values: 8 for a number and for each element of an array, the octets of a string or binary."""
    total = F.lit(0).cast("long")
    for name, kind in df.dtypes:
        if kind.startswith("array"):
            total = total + F.coalesce(F.size(name), F.lit(0)) * 8
        elif kind in ("string", "binary"):
            total = total + F.coalesce(F.octet_length(name), F.lit(0))
        else:
            total = total + 8
    return total


def machine_space(df: DataFrame, h: PolyHash, key: str = "node_id") -> DataFrame:
    """(machine, rows, bytes) under the placement of h; the sums are the total space."""
    return df.groupBy(h.column(F.col(key)).cast("long").alias("machine")).agg(F.count(F.lit(1)).alias("rows"), F.sum(row_bytes(df)).alias("bytes"))


def machine_traffic(rows: DataFrame, h: PolyHash, source: str = "node_id", target: str = "parent_id") -> DataFrame:
    """(machine, sent, received) when every row sends one message from the machine of source to that of target.

    Messages inside a machine are free; rows without a target send none.
    """
    ends = rows.where(F.col(target).isNotNull()).select(h.column(F.col(source)).cast("long").alias("a"), h.column(F.col(target)).cast("long").alias("b")).where("a <> b")
    pairs = ends.groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))
    zero = F.lit(0).cast("long")
    sent = F.struct(F.col("a").alias("machine"), F.col("n").alias("sent"), zero.alias("received"))
    received = F.struct(F.col("b").alias("machine"), zero.alias("sent"), F.col("n").alias("received"))
    return pairs.select(F.explode(F.array(sent, received)).alias("e")).select("e.*").groupBy("machine").agg(F.sum("sent").alias("sent"), F.sum("received").alias("received"))


def merge_work(ready, schedule: DataFrame, block: int) -> DataFrame:
    """(tree_id, step, half, out_part, left_n, right_n, operations, block_pairs) of a schedule, from the pieces' sizes alone.

    A part's vectors have one element more than it has original vertices; a merge multiplies
    each element of one side with each of the other, for a pair of labellings, and a grid of
    blocks deals that to block_pairs tasks. The plan is about 14 m rows a tree, so a tree's
    merges are followed in one task.
    """
    own = ready.bt.where("NOT is_aux").select("tree_id", "node_id").join(ready.dec.assign, ["tree_id", "node_id"]).groupBy("tree_id", "comp_id").agg(F.count(F.lit(1)).alias("n"))
    none, no_step = F.lit(None).cast("long"), F.lit(0)
    sizes = ready.dec.comp.select("tree_id", "comp_id").join(own, ["tree_id", "comp_id"], "left")
    sizes = sizes.select("tree_id", no_step.alias("step"), no_step.alias("half"), F.col("comp_id").alias("left_part"), none.alias("right_part"), none.alias("out_part"), F.coalesce("n", F.lit(0)).alias("n"))
    steps = schedule.select("tree_id", "step", "half", "left_part", "right_part", "out_part", none.alias("n"))

    def run(table: pa.Table) -> pa.Table:
        rows = table.to_pylist()
        size = {r["left_part"]: r["n"] for r in rows if r["right_part"] is None}
        out = []
        for r in sorted((r for r in rows if r["right_part"] is not None), key=lambda r: (r["step"], r["half"], r["right_part"])):
            a, b = size.pop(r["left_part"]), size.pop(r["right_part"])
            size[r["out_part"]] = a + b
            out.append((r["tree_id"], r["step"], r["half"], r["out_part"], a + 1, b + 1, (a + 1) * (b + 1), -(-(a + 1) // block) * -(-(b + 1) // block)))
        kinds = [pa.int64(), pa.int32(), pa.int32(), *[pa.int64()] * 5]
        return pa.table([pa.array([o[i] for o in out], k) for i, k in enumerate(kinds)], ["tree_id", "step", "half", "out_part", "left_n", "right_n", "operations", "block_pairs"])

    return sizes.unionAll(steps).groupBy("tree_id").applyInArrow(run, "tree_id long, step int, half int, out_part long, left_n long, right_n long, operations long, block_pairs long")


def partition_rows(df: DataFrame) -> DataFrame:
    """(partition, rows): space by partition."""
    return df.groupBy(F.spark_partition_id().alias("partition")).agg(F.count(F.lit(1)).alias("rows"))


def summary_size(partial: DataFrame) -> int:
    """Largest summary tensor: at most states^3 numbers."""
    return partial.agg(F.max(F.size("tensor"))).first()[0] or 0


def schedule_rows(schedule: DataFrame) -> DataFrame:
    """(tree_id, merges, steps): the plan's size and its number of turns."""
    return schedule.groupBy("tree_id").agg(F.count(F.lit(1)).alias("merges"), F.max("step").alias("steps"))


def space_in_blocks(blocks: DataFrame) -> DataFrame:
    """(elements, largest_block, rows) of vectors in blocks: total and per-row space."""
    return blocks.agg(F.sum(F.size("vals")).alias("elements"), F.max(F.size("vals")).alias("largest_block"), F.count(F.lit(1)).alias("rows"))


def success_share(tree: DataFrame, m: int, seeds: int = 5) -> float:
    """Share of seeds for which every decomposition bound holds."""
    from .operators.finite import prepare_tree

    good = 0
    for seed in range(seeds):
        ready = prepare_tree(tree, m, seed)
        good += all(check_decomposition(ready.bt, ready.dec).values())
    return good / seeds


def independent_set_weight(tree: DataFrame, states: DataFrame) -> DataFrame:
    """(weight, inner_edges) of a recovered set, checked by plain joins."""
    chosen = states.where("state = 'I'").select("tree_id", "node_id")
    inside = materialise(tree.join(chosen, ["tree_id", "node_id"]), "chosen")
    up = inside.select("tree_id", F.col("node_id").alias("parent_id"))
    pairs = inside.join(up, ["tree_id", "parent_id"], "left_semi")
    return inside.agg(F.sum("node_w").alias("weight")).crossJoin(pairs.agg(F.count(F.lit(1)).alias("inner_edges")))
