"""Data model: schemas, validation and the machine budget."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TREE = "tree_id long, node_id long, parent_id long, child_ord int, node_w long, edge_w long"
BINTREE = "tree_id long, node_id long, parent_id long, is_aux boolean, origin_id long, node_w long, edge_w long"
ASSIGN = "tree_id long, node_id long, comp_id long"
COMP = "tree_id long, comp_id long, parent_comp long, attach_node long, n_vertices long, n_children int, completed boolean, iteration int"
ANSWER = "tree_id long, problem string, param long, value long, feasible boolean"
METRICS = "run_id string, stage string, superstep int, measure string, value double"

#: Stands for minus infinity in exact integer arithmetic; sums are clamped to it.
NEG = -(1 << 60)
MAX_NODE_ID = (1 << 61) - 1


@dataclass(frozen=True)
class Budget:
    """Space and machine limits of the parallel model for n vertices on m machines."""

    n: int
    m: int
    family: str = "finite"
    log_power: int = 1

    def space_per_machine(self) -> float:
        """Vertices (or vector elements) a machine may hold, with log^c slack."""
        slack = max(1.0, math.log2(max(2, self.n))) ** self.log_power
        total = self.n if self.family == "finite" else self.n ** (4 / 3)
        return total / self.m * slack

    def total_space(self) -> float:
        return self.m * self.space_per_machine()

    def max_machines(self, eps: float = 1 / 3) -> int:
        return max_machines(self.n, eps) if self.family == "linear" else max(1, math.isqrt(self.n))

    def is_allowed(self) -> bool:
        return 1 <= self.m <= max(1, self.max_machines())


def max_machines(n: int, eps: float = 1 / 3) -> int:
    """From n/sqrt(m) <= n^(1+eps)/m: m may grow to n^(1+eps) squared-rooted, that is n^((1+eps)/2)."""
    return max(1, int(n ** ((1 + eps) / 2)))


class InvalidTree(ValueError):
    pass


def validate(tree: DataFrame) -> dict[str, int]:
    """Checks one root per tree, unique ids in range, parents that exist, and no cycle. Raises InvalidTree.

    Cycles are found by pointer doubling: after ceil(log2 n)+1 joins every vertex
    of a tree has jumped to its root.
    """
    from .plans.iterate import materialise

    keys = ["tree_id", "node_id"]
    n = tree.count()
    bad = {"ids out of range": tree.where((F.col("node_id") < 0) | (F.col("node_id") > MAX_NODE_ID) | F.col("node_id").isNull()).count()}
    bad["repeated ids"] = tree.groupBy(*keys).count().where("count > 1").count()
    roots = tree.groupBy("tree_id").agg(F.sum(F.col("parent_id").isNull().cast("int")).alias("r"))
    bad["trees without exactly one root"] = roots.where("r <> 1").count()
    parents = tree.select("tree_id", F.col("node_id").alias("parent_id"))
    bad["dangling parents"] = tree.where("parent_id IS NOT NULL").join(parents, ["tree_id", "parent_id"], "left_anti").count()
    found = {k: v for k, v in bad.items() if v}
    if found:
        raise InvalidTree(f"invalid tree: {found}")
    ptr = materialise(tree.select(*keys, F.coalesce("parent_id", "node_id").alias("ptr"), F.col("parent_id").isNull().alias("at_root")), "validate")
    for _ in range(max(1, math.ceil(math.log2(max(2, n)))) + 1):
        up = ptr.select("tree_id", F.col("node_id").alias("ptr"), F.col("ptr").alias("next"), F.col("at_root").alias("up_root"))
        ptr = materialise(
            ptr.join(up, ["tree_id", "ptr"]).select("tree_id", "node_id", F.col("next").alias("ptr"), (F.col("at_root") | F.col("up_root")).alias("at_root")),
            "validate",
        )
        lost = ptr.where("NOT at_root").limit(1).count()
        if not lost:
            return {"vertices": n, "trees": roots.count()}
    raise InvalidTree("invalid tree: a cycle")


def empty(spark: SparkSession, schema: str) -> DataFrame:
    return spark.createDataFrame([], schema)
