"""Joining the summaries of small-state pieces by the merge schedule, for contracted trees too large for one task."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import NEG
from ..plans import schedule as plan
from ..plans.iterate import materialise, prepare
from .finite import Tables
from .problems import Problem

GENERAL = "tree_id long, part_id long, leaves array<long>, tensor array<long>"


def _general(tensor: np.ndarray, leaves: int, s: int) -> np.ndarray:
    """[s] + [s] * leaves, from a piece's tensor."""
    t = np.asarray(tensor, np.int64).reshape(s, -1)
    if leaves == 0:
        return t[:, 0]
    t = t.reshape(s, s, s)
    return t[:, :, 0] if leaves == 1 else t


def contract(upper: np.ndarray, axis: int, lower: np.ndarray) -> np.ndarray:
    """(max,+) product: the lower part's root state meets the upper part's leaf on the axis; the lower part's leaves come last."""
    moved = np.moveaxis(upper, axis, -1)
    flat_upper = moved.reshape(-1, moved.shape[-1])
    flat_lower = lower.reshape(lower.shape[0], -1)
    out = np.full((flat_upper.shape[0], flat_lower.shape[1]), NEG, np.int64)
    for x in range(flat_lower.shape[0]):
        np.maximum(out, flat_upper[:, x : x + 1] + flat_lower[x : x + 1, :], out=out)
    return np.maximum(out, NEG).reshape(*moved.shape[:-1], *lower.shape[1:])


def finish_scheduled(partial: DataFrame, comp: DataFrame, problem: Problem) -> DataFrame:
    """ANSWER of every tree; each turn merges disjoint pairs of parts, which have at most four open ends."""
    spark = partial.sparkSession
    prepare(spark)
    s = len(problem.states)
    merges = materialise(plan.build(comp), "merges")

    def widen(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            leaves = batch.column("leaf_comps").to_pylist()
            tensors = [_general(np.array(t, np.int64), len(x), s).reshape(-1).tolist() for t, x in zip(batch.column("tensor").to_pylist(), leaves)]
            yield pa.RecordBatch.from_arrays([batch.column("tree_id"), batch.column("comp_id"), pa.array(leaves, pa.list_(pa.int64())), pa.array(tensors, pa.list_(pa.int64()))], ["tree_id", "part_id", "leaves", "tensor"])

    def join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows: list[list] = [[], [], [], []]
            for r in batch.to_pylist():
                upper = np.array(r["u_tensor"], np.int64).reshape([s] * (1 + len(r["u_leaves"])))
                lower = np.array(r["l_tensor"], np.int64).reshape([s] * (1 + len(r["l_leaves"])))
                axis = r["u_leaves"].index(r["child_comp"])
                out = contract(upper, axis + 1, lower)
                leaves = [x for x in r["u_leaves"] if x != r["child_comp"]] + r["l_leaves"]
                for column, value in zip(rows, (r["tree_id"], r["out_part"], leaves, out.reshape(-1).tolist())):
                    column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(rows[0], pa.int64()), pa.array(rows[1], pa.int64()), pa.array(rows[2], pa.list_(pa.int64())), pa.array(rows[3], pa.list_(pa.int64()))], ["tree_id", "part_id", "leaves", "tensor"])

    parts = materialise(partial.select("tree_id", "comp_id", "leaf_comps", "tensor").mapInArrow(widen, GENERAL), "parts")
    for step, half in plan.steps_of(merges):
        now = merges.where((F.col("step") == step) & (F.col("half") == half)).select("tree_id", "child_comp", "left_part", "right_part", "out_part")
        upper = parts.select("tree_id", F.col("part_id").alias("left_part"), F.col("leaves").alias("u_leaves"), F.col("tensor").alias("u_tensor"))
        lower = parts.select("tree_id", F.col("part_id").alias("right_part"), F.col("leaves").alias("l_leaves"), F.col("tensor").alias("l_tensor"))
        merged = now.join(upper, ["tree_id", "left_part"]).join(lower, ["tree_id", "right_part"]).mapInArrow(join, GENERAL)
        used = now.select("tree_id", F.explode(F.array("left_part", "right_part")).alias("part_id"))
        parts = materialise(parts.join(used, ["tree_id", "part_id"], "left_anti").select("tree_id", "part_id", "leaves", "tensor").unionAll(merged), "parts")
    t = Tables(problem)
    best = F.array_max(F.transform(F.array(*[F.lit(i) for i in t.final]), lambda i: F.get("tensor", i)))
    feasible = best > NEG // 2
    return parts.select("tree_id", F.lit(problem.name).alias("problem"), F.lit(None).cast("long").alias("param"), F.when(feasible, best * t.sign).alias("value"), feasible.alias("feasible"))
