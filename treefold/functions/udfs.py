"""SQL surface: table functions over partitions of a tree table, and Arrow functions where expressions do not reach."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from ..model import NEG
from ..operators.finite import Tables, fold
from ..operators.problems import PROBLEMS
from ..plans.decompose import positions
from ..plans.hashing import PolyHash
from ..plans.iterate import prepare


@udtf(returnType="tree_id bigint, problem string, value bigint")
class TreeDp:
    """tree_dp(TABLE(tree) PARTITION BY (tree_id), 'mis'): each tree folded in one task; for forests of small trees in SQL."""

    def __init__(self):
        self.rows, self.problem = [], None

    def eval(self, row, problem: str):
        self.problem = problem
        self.rows.append((row["tree_id"], row["node_id"], -1 if row["parent_id"] is None else row["parent_id"], row["node_w"] or 0, row["edge_w"] or 0))

    def terminate(self):
        if not self.rows:
            return
        a = np.array(sorted(self.rows), np.int64)
        t = Tables(PROBLEMS[self.problem]())
        parent = positions(a[:, 0].copy(), a[:, 1].copy(), a[:, 2].copy())
        value = fold(t, parent, np.zeros(len(a), bool), a[:, 3], a[:, 4], np.zeros(0, np.int64), np.zeros((0, t.s, 1), np.int64), 1)
        for r in np.flatnonzero(parent < 0).tolist():
            yield int(a[r, 0]), t.problem.name, t.best(value[r, :, 0])


@udtf(returnType="tree_id bigint, step int, half int, child_comp bigint, left_part bigint, right_part bigint, out_part bigint")
class SplitPlan:
    """split_plan(TABLE(comp) PARTITION BY tree_id): the merge schedule of a tree of pieces."""

    def __init__(self):
        self.parents, self.tree = {}, None

    def eval(self, row):
        self.tree = row["tree_id"]
        self.parents[row["comp_id"]] = row["parent_comp"]

    def terminate(self):
        from ..plans.schedule import build_plan

        for merge in build_plan(self.parents) if self.parents else []:
            yield (self.tree, *merge)


@udtf(returnType="depth int, prefix string")
class ExplodePath:
    """explode_path(url): host label suffixes, from the last label on, then the host with its first path part."""

    def eval(self, url: str):
        from urllib.parse import urlsplit

        if not url:
            return
        parts = urlsplit(url)
        labels = (parts.hostname or "").split(".")[::-1]
        for i in range(len(labels)):
            yield i + 1, ".".join(labels[: i + 1])
        yield len(labels) + 1, ".".join(labels) + "/" + (parts.path.split("/") + [""])[1]


def register(spark: SparkSession) -> None:
    prepare(spark)
    spark.udtf.register("tree_dp", TreeDp)
    spark.udtf.register("split_plan", SplitPlan)
    spark.udtf.register("explode_path", ExplodePath)


def poly_hash_udf(h: PolyHash):
    """The hash modulo 2^31 - 1 on Arrow batches; the native expression is faster, this is its reference."""

    @pandas_udf("int")
    def run(keys: pd.Series) -> pd.Series:
        return pd.Series(h.evaluate(keys.to_numpy()).astype(np.int32))

    return run


def tensor_merge(states: int, slot: int):
    """Arrow function: summary of two touching pieces (child [s, s], parent [s, s, s])."""
    from ..operators.finite import merge

    @pandas_udf("array<long>")
    def run(child: pd.Series, parent: pd.Series) -> pd.Series:
        return pd.Series([merge(np.asarray(c), np.asarray(p), slot, states).reshape(-1).tolist() for c, p in zip(child, parent)])

    return run


def fold_children(column: str, states: int) -> Column:
    """Element-wise sum of the children's vectors in a grouped aggregation, as native sums; minus infinity absorbs."""
    return F.array(*[F.greatest(F.sum(F.get(F.col(column), i)), F.lit(NEG)) for i in range(states)])
