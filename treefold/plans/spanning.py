"""Minimum spanning tree of vectors by squared distance, by rounds of hooking (each component takes its lightest outgoing edge)."""

from __future__ import annotations


import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .iterate import materialise, prepare

SCALE = 1000
BLOCK = 2048
#: Pairs whose exact distances are computed at once.
EXACT_PAIRS = 100_000


def products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Scaled squared distances of all pairs by one matrix product; good to about 1e-12 of the squared lengths."""
    return ((a * a).sum(axis=1)[:, None] + (b * b).sum(axis=1)[None, :] - 2.0 * (a @ b.T)) * SCALE


def least_of_rows(x: np.ndarray, rows: np.ndarray, cols: np.ndarray, near: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, column, weight) of the least whole distance of each row that has any, of equal ones the first column.

    near only says which pairs may be the least: their distances are computed again from the differences.
    """
    # rounding moves a distance by a half at most, so the least ones lie within 1 of each other before it
    slack = 1.001 + 1e-9 * SCALE * float((x * x).sum(axis=1).max(initial=0.0))
    best = near.min(axis=1)
    mine, other, weight = [], [], []
    some = np.flatnonzero(np.isfinite(best))
    step = max(1, EXACT_PAIRS // max(1, near.shape[1]))
    for at in range(0, len(some), step):
        part = some[at : at + step]
        i, j = np.nonzero(near[part] <= best[part, None] + slack)
        w = np.rint(((x[rows[part[i]]] - x[cols[j]]) ** 2).sum(axis=1) * SCALE).astype(np.int64)
        order = np.lexsort((j, w, i))
        i, j, w = i[order], j[order], w[order]
        first = np.r_[True, i[1:] != i[:-1]]
        mine.append(rows[part[i[first]]])
        other.append(cols[j[first]])
        weight.append(w[first])
    if not mine:
        return (np.zeros(0, np.int64),) * 3
    return np.concatenate(mine), np.concatenate(other), np.concatenate(weight)


def lightest_outgoing(vectors: DataFrame, label: DataFrame, blocks: int) -> DataFrame:
    """(ra, to, w, a, b): the lightest edge (ties by ids) that leaves each component, a < b.

    A pair of blocks of vectors meets in a task, which sends on one edge for each
    component it holds; distances are never written, but computed again in each round.
    """
    prepare(vectors.sparkSession)
    rows = vectors.select(F.col("vec_id").alias("id"), "embedding").join(label, "id").withColumn("side", F.pmod("id", F.lit(blocks)).cast("int"))
    pairs = F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), lambda o: F.struct(F.least(o, F.col("side")).alias("one"), F.greatest(o, F.col("side")).alias("two")))
    dealt = rows.withColumn("p", F.explode(pairs)).select("id", "root", "embedding", "side", "p.one", "p.two")

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("id")
        ids, roots, side = table["id"].to_numpy(), table["root"].to_numpy(), table["side"].to_numpy()
        x = np.array(table["embedding"].to_pylist(), np.float64)
        left, right = np.flatnonzero(side == table["one"][0].as_py()), np.flatnonzero(side == table["two"][0].as_py())
        found = []
        if len(left) and len(right):
            near = products(x[left], x[right])
            near[roots[left][:, None] == roots[right][None, :]] = np.inf
            for rows_, cols, m in ((left, right, near), (right, left, near.T)):
                mine, other, w = least_of_rows(x, rows_, cols, m)
                found.append(np.stack([roots[mine], roots[other], w, np.minimum(ids[mine], ids[other]), np.maximum(ids[mine], ids[other])]))
        edges = np.concatenate(found, axis=1) if found else np.zeros((5, 0), np.int64)
        edges = edges[:, np.lexsort((edges[4], edges[3], edges[2], edges[0]))]
        first = np.ones(edges.shape[1], bool)
        first[1:] = edges[0, 1:] != edges[0, :-1]
        return pa.table([pa.array(c[first]) for c in edges], ["ra", "to", "w", "a", "b"])

    sent = dealt.groupBy("one", "two").applyInArrow(run, "ra long, to long, w long, a long, b long")
    return sent.groupBy("ra").agg(F.min(F.struct("w", "a", "b", "to")).alias("m")).select("ra", "m.to", "m.w", "m.a", "m.b")


def spanning_tree(vectors: DataFrame, root: int = 0) -> DataFrame:
    """TREE of the minimum spanning tree (ties by ids), rooted; vertex weights 1."""
    blocks = max(1, -(-vectors.count() // BLOCK))
    label = materialise(vectors.select(F.col("vec_id").alias("id"), F.col("vec_id").alias("root")), "labels")
    chosen = None
    while label.select("root").distinct().limit(2).count() > 1:
        best = materialise(lightest_outgoing(vectors, label, blocks), "lightest")
        new = best.select("a", "b", "w").distinct()
        chosen = materialise(new if chosen is None else chosen.unionAll(new), "chosen")
        # hooks form stars of pairs: the smaller end of each mutual pair is the new root
        back = best.select(F.col("ra").alias("to"), F.col("to").alias("back"))
        hook = best.join(back, "to", "left").select(F.col("ra").alias("id"), F.when((F.col("back") == F.col("ra")) & (F.col("ra") < F.col("to")), F.col("ra")).otherwise(F.col("to")).alias("up"))
        hook = materialise(hook, "hooks")
        while True:
            far = hook.select(F.col("id").alias("up"), F.col("up").alias("next"))
            after = materialise(hook.join(far, "up").select("id", F.col("next").alias("up"), (F.col("next") != F.col("up")).alias("moved")), "hooks")
            if not after.where("moved").limit(1).count():
                break
            hook = after.drop("moved")
        label = materialise(label.join(hook.select(F.col("id").alias("root"), "up"), "root").select("id", F.col("up").alias("root")), "labels")
    if chosen is None:
        return vectors.selectExpr("0L AS tree_id", "vec_id AS node_id", "cast(NULL AS bigint) AS parent_id", "0 AS child_ord", "1L AS node_w", "cast(NULL AS bigint) AS edge_w")
    from ..sources.files import root_edges

    rooted = root_edges(chosen, root, method="euler")
    return rooted.selectExpr("0L AS tree_id", "node_id", "parent_id", "0 AS child_ord", "1L AS node_w", "edge_w")


