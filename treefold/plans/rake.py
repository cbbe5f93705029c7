"""Subtree sizes of a tree that forks often, and which of some vertices is the closest above others.

The tree's leaves are taken off in turns. A turn is one grouping by vertex: a vertex whose children
are all gone leaves in the next one and gives its size to its parent. While a turn takes off a good
share of the rows the turns' tables shrink by a constant factor; once a table is no longer than one
machine's space, one task finishes it on arrays. Vertices may have any number of children.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .decompose import local_space, positions
from .iterate import materialise, measured, prepare, release

#: A turn takes off this share of the rows at least; a tree with long paths is left to the decomposition.
LEAST_SHARE = 0.125


@dataclass
class Raked:
    """turns: rows (node_id, parent_id, w, size, open) of each turn, of which those with open = 0 left. rest: the rows that stayed."""

    turns: list[DataFrame]
    rest: DataFrame


def _grouped(rows: DataFrame, gifts: DataFrame) -> DataFrame:
    none = F.lit(None).cast("long")
    every = rows.unionAll(gifts.select("node_id", none, none, "size", "open"))
    return every.groupBy("node_id").agg(*[F.max(c).alias(c) for c in ("parent_id", "w")], *[F.sum(c).alias(c) for c in ("size", "open")])


def rake(tree: DataFrame, n: int, m: int) -> Raked | None:
    """Takes the leaves of a single tree of n vertices off in turns. None: a turn took off too few, or rows are no tree."""
    prepare(tree.sparkSession)
    zero, one = F.lit(0).cast("long"), F.lit(1).cast("long")
    rows = tree.select("node_id", "parent_id", F.coalesce("edge_w", zero).alias("w"), one.alias("size"), zero.alias("open"))
    kids = tree.where("parent_id IS NOT NULL").select(F.col("parent_id").alias("node_id"), zero.alias("size"), one.alias("open"))
    counts = {"rows": F.count(F.lit(1)), "gone": F.count_if(F.col("open") == 0)}
    table, seen = measured(_grouped(rows, kids), "raked", **counts)
    turns: list[DataFrame] = []
    most = local_space(n, m)
    left = n
    while seen["rows"] == left and left > most and seen["gone"] >= LEAST_SHARE * left:
        turns.append(table)
        left -= seen["gone"]
        gifts = table.where("open = 0 AND parent_id IS NOT NULL").select(F.col("parent_id").alias("node_id"), "size", (-one).alias("open"))
        table, seen = measured(_grouped(table.where("open > 0"), gifts), "raked", **counts)
    if seen["rows"] != left or left > most:
        release(*turns, table)
        return None
    return Raked(turns, table)


def _arrays(batches: Iterator[pa.RecordBatch]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray] | None:
    """(node, position of the parent, weight, size) of the rows that stayed, by node."""
    held = list(batches)
    if not held:
        return None
    table = pa.Table.from_batches(held)
    node, above, w, size = (table[c].fill_null(-1).to_numpy() for c in ("node_id", "parent_id", "w", "size"))
    order = np.argsort(node)
    node, above, w, size = (x[order] for x in (node, above, w, size))
    return node, positions(np.zeros(len(node), np.int64), node, above), w, size


def _largest(most: int):
    """The `most` rows with the largest size to weight, no weight coming first, with whole sizes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if (got := _arrays(batches)) is None:
            return
        node, par, w, size = got
        depth, ptr = (par >= 0).astype(np.int64), np.where(par >= 0, par, np.arange(len(par)))
        while not np.array_equal(far := ptr[ptr], ptr):
            depth, ptr = depth + depth[ptr], far
        sums, ups = size.tolist(), par.tolist()
        for v in np.argsort(-depth, kind="stable").tolist():
            if ups[v] >= 0:
                sums[ups[v]] += sums[v]
        size = np.array(sums, np.int64)
        at = np.flatnonzero(par >= 0)
        ratio = np.where(w[at] <= 0, np.inf, size[at] / np.maximum(w[at], 1))
        at = at[np.lexsort((node[at], w[at], -ratio))[:most]]
        yield pa.RecordBatch.from_arrays([pa.array(x[at]) for x in (node, w, size)] + [pa.array(node[par[at]])], ["node_id", "w", "size", "parent_id"])

    return run


def largest(raked: Raked, most: int) -> list[tuple[int, int, int, int]]:
    """(vertex, weight, size of its subtree, parent) of the `most` edges with the largest size to weight, no weight coming first."""
    schema = "node_id long, w long, size long, parent_id long"
    tops = materialise(raked.rest.select("node_id", "parent_id", "w", "size").coalesce(1).mapInArrow(_largest(most), schema), "largest")
    for table in raked.turns:
        tops = tops.unionAll(table.where("open = 0 AND parent_id IS NOT NULL").select("node_id", "w", "size", "parent_id"))
    ratio = F.when(F.col("w") <= 0, F.lit(float("inf"))).otherwise(F.col("size") / F.col("w"))
    return [tuple(r) for r in tops.orderBy(ratio.desc(), "w", "node_id").limit(most).collect()]


def closest(raked: Raked, parents: dict[int, int]) -> dict[int, int]:
    """The closest vertex above each one that is among them too, or the root. parents: the parent of each."""
    spark = raked.rest.sparkSession
    at = dict(parents)
    for table in raked.turns:
        # who left in a turn has a parent that left in a later one
        asked = spark.createDataFrame(pa.table({"node_id": pa.array([*({*at.values()} - parents.keys())], pa.int64())}))
        up = {r["node_id"]: r["parent_id"] for r in table.where("open = 0").join(F.broadcast(asked), "node_id").select("node_id", "parent_id").collect()}
        at = {v: up.get(p, p) if p not in parents else p for v, p in at.items()}
    asked = np.array(sorted({*at.values()} - parents.keys()), np.int64)
    marked = np.array(sorted(parents), np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if (got := _arrays(batches)) is None:
            return
        node, par, _, _ = got
        ptr = np.where((par < 0) | np.isin(node, marked), np.arange(len(par)), par)
        while not np.array_equal(far := ptr[ptr], ptr):
            ptr = far
        yield pa.RecordBatch.from_arrays([pa.array(asked), pa.array(node[ptr[np.searchsorted(node, asked)]])], ["node_id", "top"])

    rest = raked.rest.select("node_id", "parent_id", "w", "size").coalesce(1).mapInArrow(run, "node_id long, top long")
    top = {r["node_id"]: r["top"] for r in rest.collect()}
    return {v: top.get(p, p) for v, p in at.items()}
