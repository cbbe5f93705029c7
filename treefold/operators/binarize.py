"""Degrees and the binary extension of a tree.

Phase one caps the degree of vertices with very many children: each gets up to
`cap` helpers, and every child is dealt to one by a seeded hash. Phase two
brings the children of a vertex together (now at most about `cap` rows) and
lays a binary shape of helpers over them. Helpers are named after children, so
no global counter is needed: an id is the child's id shifted left by two bits,
with tag 1 (phase two), 2 (phase one) or 3 (phase two, over a phase-one helper).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.columns import tagged

SHAPES = ("balanced", "comb")
#: Most children that phase one leaves beside each other, as a task holds them as one array.
MOST_CHILDREN = 20_000


def degrees(tree: DataFrame) -> DataFrame:
    """(tree_id, node_id, degree): children of every vertex, 0 for leaves.

    The partial aggregation sends at most one count per vertex and task.
    """
    counted = tree.where("parent_id IS NOT NULL").groupBy("tree_id", F.col("parent_id").alias("node_id")).agg(F.count(F.lit(1)).alias("degree"))
    return tree.select("tree_id", "node_id").join(counted, ["tree_id", "node_id"], "left").select("tree_id", "node_id", F.coalesce("degree", F.lit(0)).alias("degree"))


def start(tree: DataFrame) -> DataFrame:
    """The tree in tagged ids, nothing added yet."""
    return tree.select("tree_id", tagged(F.col("node_id")).alias("node_id"), tagged(F.col("parent_id")).alias("parent_id"), "child_ord", F.lit(False).alias("is_aux"), tagged(F.col("node_id")).alias("origin_id"), "node_w", "edge_w")


def cap_degree(tagged_tree: DataFrame, cap: int, seed: int = 0) -> DataFrame:
    """Phase one on tagged rows: no vertex keeps more than about max(cap, degree / cap) children.

    The hot vertices are few (at most n / cap); Spark broadcasts them only under its own size limit.
    """
    counted = tagged_tree.where("parent_id IS NOT NULL").groupBy("tree_id", "parent_id").agg(F.count(F.lit(1)).alias("k"))
    hot = counted.where(F.col("k") > cap).select("tree_id", "parent_id", F.least(F.lit(cap), F.ceil(F.col("k") / cap)).cast("long").alias("slots"))
    dealt = tagged_tree.join(hot, ["tree_id", "parent_id"], "left").withColumn("slot", F.when(F.col("slots").isNotNull(), F.pmod(F.xxhash64(F.lit(seed), "node_id"), F.col("slots"))))
    names = dealt.where("slot IS NOT NULL").groupBy("tree_id", "parent_id", "slot").agg(F.min("node_id").alias("named"))
    helper = F.col("named").bitwiseOR(F.lit(2))
    moved = dealt.join(names, ["tree_id", "parent_id", "slot"], "left").withColumn("parent_id", F.coalesce(helper, "parent_id"))
    columns = ["tree_id", "node_id", "parent_id", "child_ord", "is_aux", "origin_id", "node_w", "edge_w"]
    helpers = names.select("tree_id", helper.alias("node_id"), "parent_id", F.col("slot").cast("int").alias("child_ord"), F.lit(True).alias("is_aux"), F.col("parent_id").alias("origin_id"), F.lit(0).cast("long").alias("node_w"), F.lit(0).cast("long").alias("edge_w"))
    return moved.select(*columns).unionAll(helpers.select(*columns))


def _helper_name(child: Column) -> Column:
    """Tag 1 on an original child, tag 3 on a phase-one helper (whose tag is 2)."""
    return child.bitwiseOR(F.lit(1))


def to_binary(capped: DataFrame, shape: str = "balanced") -> DataFrame:
    """Phase two: at most two children each. Needs the children of a vertex to fit a task (see cap_degree).

    Balanced: children are the leaves k..2k-1 of a heap whose node 1 is the vertex and whose
    nodes 2..k-1 are helpers. Comb: helpers form a path that takes one child each.
    """
    if shape not in SHAPES:
        raise ValueError(f"shape must be one of {SHAPES}")
    columns = ["tree_id", "node_id", "parent_id", "is_aux", "origin_id", "node_w", "edge_w"]
    roots = capped.where("parent_id IS NULL").select(*columns)
    child = F.struct("child_ord", "node_id", "is_aux", "origin_id", "node_w", "edge_w")
    families = capped.where("parent_id IS NOT NULL").groupBy("tree_id", "parent_id").agg(F.array_sort(F.collect_list(child)).alias("kids"))
    # the origin of a helper is the nearest original vertex above: the parent, or its origin when it is a phase-one helper
    helper_origins = capped.where("is_aux").select("tree_id", F.col("node_id").alias("parent_id"), F.col("origin_id").alias("above"))
    families = families.join(helper_origins, ["tree_id", "parent_id"], "left").withColumn("above", F.coalesce("above", "parent_id"))
    k = F.size("kids")

    def name_of(rank: Column) -> Column:
        return _helper_name(F.get("kids", rank.cast("int"))["node_id"])

    if shape == "balanced":

        def parent_of(place):
            up = F.floor(place / 2)
            return F.when(up <= 1, F.col("parent_id")).otherwise(name_of(up - 2))

        child_place, helper_place = (lambda r: k + r), (lambda j: j + 2)
    else:

        def parent_of(place):
            return F.when(place < 0, F.col("parent_id")).otherwise(name_of(place))

        child_place, helper_place = (lambda r: F.least(r, k - 2) - 1), (lambda j: j - 1)

    def child_row(kid, r):
        above = F.when(k <= 2, F.col("parent_id")).otherwise(parent_of(child_place(r)))
        return F.struct(kid["node_id"].alias("node_id"), above.alias("parent_id"), kid["is_aux"].alias("is_aux"), kid["origin_id"].alias("origin_id"), kid["node_w"].alias("node_w"), kid["edge_w"].alias("edge_w"))

    def helper_row(j):
        zero = F.lit(0).cast("long")
        return F.struct(name_of(j).alias("node_id"), parent_of(helper_place(j)).alias("parent_id"), F.lit(True).alias("is_aux"), F.col("above").alias("origin_id"), zero.alias("node_w"), zero.alias("edge_w"))

    helpers = F.when(k > 2, F.transform(F.sequence(F.lit(0), F.greatest(k - 3, F.lit(0))), helper_row))
    rows = F.concat(F.transform("kids", child_row), F.coalesce(helpers, F.slice(F.transform("kids", child_row), 1, 0)))
    out = families.select("tree_id", F.explode(rows).alias("r")).select("tree_id", "r.*")
    return roots.unionAll(out.select(*columns))


def default_cap(n: int, m: int) -> int:
    """A machine's share of the vertices, within what one row may hold."""
    return min(MOST_CHILDREN, max(2, -(-n // max(1, m))))


def binary_extension(tree: DataFrame, cap: int | None = 100_000, seed: int = 0, shape: str = "balanced", started: DataFrame | None = None) -> DataFrame:
    """The binary extension; cap=None leaves out phase one (a baseline: one task then gets all children of a vertex). started: start() of the tree, where it is there."""
    rows = start(tree) if started is None else started
    if cap is not None:
        rows = cap_degree(rows, cap, seed)
    return to_binary(rows, shape)
