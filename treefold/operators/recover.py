"""A solution set from the engine: states chosen from the roots down, piece by piece."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import NEG
from ..plans.iterate import materialise, prepare
from .finite import Prepared, Tables, _piece_arrays, _slots, _sorted_runs, compress, evaluate, fold, piece_rows, prepare_tree
from .problems import Problem


def _choose(problem: Problem):
    """Root state of every piece: the best final state at the top, then what the piece above wants of its leaves."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = Tables(problem)
        s = t.s
        for table in _sorted_runs(batches, ["tree_id"]):
            at = {(r["tree_id"], r["comp_id"]): r for r in table.to_pylist()}
            below = {(tree, c) for (tree, _), r in at.items() for c in r["leaf_comps"]}
            done: dict[tuple[int, int], np.ndarray] = {}
            state: dict[tuple[int, int], int] = {}
            for key in (k for k in at if k not in below):
                order = [key]
                for k in order:
                    order += [(k[0], c) for c in at[k]["leaf_comps"]]
                for k in reversed(order):
                    done[k] = evaluate(at[k]["tensor"], [done[(k[0], c)] for c in at[k]["leaf_comps"]], s)
                state[key] = max(t.final, key=lambda i: (done[key][i], -i))
                for k in order:
                    kids = [(k[0], c) for c in at[k]["leaf_comps"]]
                    if not kids:
                        continue
                    cell = np.array(at[k]["tensor"], np.int64).reshape(s, s, s)[state[k]]
                    total = cell + done[kids[0]][:, None] + (done[kids[1]][None, :] if len(kids) == 2 else np.where(np.arange(s) == 0, 0, 4 * NEG)[None, :])
                    a, b = np.unravel_index(int(np.argmax(total)), total.shape)
                    for kid, choice in zip(kids, (a, b)):
                        state[kid] = int(choice)
            keys = list(state)
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys], pa.int64()), pa.array([k[1] for k in keys], pa.int64()), pa.array([state[k] for k in keys], pa.int32()), pa.array([done[k].tolist() for k in keys], pa.list_(pa.int64()))], ["tree_id", "comp_id", "state", "vector"])

    return run


def _trace(problem: Problem):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = Tables(problem)
        for table in _sorted_runs(batches, ["tree_id", "comp_id"]):
            tree, comp, node, parent, aux, node_w, edge_w, leaf, code, order = _piece_arrays(table)
            at, _ = _slots(code, leaf)
            known = table["vector"].to_pylist()
            given = table["state"].fill_null(-1).to_numpy()[order]
            vectors = np.array([known[int(order[a])] for a in at], np.int64).reshape(-1, t.s, 1)
            value = fold(t, parent, aux, node_w, edge_w, at, vectors, 1)
            kids: list[list[int]] = [[] for _ in node]
            for i, p in enumerate(parent.tolist()):
                if p >= 0:
                    kids[p].append(i)
            state = np.full(len(node), -1, np.int64)
            via = np.full(len(node), -1, np.int64)  # state as the parent sees it
            todo = np.flatnonzero((parent < 0) & (leaf < 0)).tolist()
            for r in todo:
                state[r] = given[r]
            while todo:
                v = todo.pop()
                if leaf[v] >= 0 or not kids[v]:
                    continue
                # undo the joins of this vertex's children, last first
                steps = [t.start(aux[v : v + 1], node_w[v : v + 1], 1)]
                seen = [t.lifted(value[c : c + 1], aux[c : c + 1], edge_w[c : c + 1]) for c in kids[v]]
                for x in seen:
                    steps.append(t.joined(steps[-1], x))
                want = int(state[v])
                for i in range(len(kids[v]) - 1, -1, -1):
                    c = kids[v][i]
                    total = int(steps[i + 1][0, want, 0])
                    a, b = next((a, b) for a, b, z in t.join if z == want and int(steps[i][0, a, 0]) + int(seen[i][0, b, 0]) == total)
                    via[c] = b
                    if aux[c]:
                        state[c] = b
                    else:
                        w = t.sign * (1 if problem.unit else int(edge_w[c]))
                        state[c] = next(x for x, y, weighted in t.lift if y == b and int(value[c, x, 0]) + (w if weighted else 0) == int(seen[i][0, b, 0]))
                    want = a
                    todo.append(c)
            keep = np.flatnonzero(~aux & (leaf < 0))
            yield pa.RecordBatch.from_arrays([pa.array(tree[keep]), pa.array(node[keep] >> 2), pa.array([problem.states[i] for i in state[keep]])], ["tree_id", "node_id", "state"])

    return run


def recover(tree: DataFrame | Prepared, problem: Problem, m: int | None = None, seed: int = 0) -> DataFrame:
    """(tree_id, node_id, state) of one best solution for every original vertex.

    For label problems the state is the label; for matching, M marks a vertex matched to a child.
    """
    ready = tree if isinstance(tree, Prepared) else prepare_tree(tree, m, seed)
    prepare(ready.bt.sparkSession)
    partial = compress(ready.bt, ready.dec, problem)
    chosen = materialise(partial.repartition("tree_id").sortWithinPartitions("tree_id").mapInArrow(_choose(problem), "tree_id long, comp_id long, state int, vector array<long>"), "states")
    rows = piece_rows(ready.bt, ready.dec).select("tree_id", "comp_id", "node_id", "parent_id", "is_aux", "node_w", "edge_w", "leaf")
    own = rows.where("leaf IS NULL").join(chosen.select("tree_id", "comp_id", "state"), ["tree_id", "comp_id"]).withColumn("vector", F.lit(None).cast("array<bigint>"))
    leaves = rows.where("leaf IS NOT NULL").join(chosen.select("tree_id", F.col("comp_id").alias("leaf"), "vector"), ["tree_id", "leaf"]).withColumn("state", F.lit(None).cast("int"))
    joined = own.unionByName(leaves)
    return joined.repartition("tree_id", "comp_id").sortWithinPartitions("tree_id", "comp_id").mapInArrow(_trace(problem), "tree_id long, node_id long, state string")


def matched_edges(tree: DataFrame | Prepared, original: DataFrame, m: int | None = None, seed: int = 0) -> DataFrame:
    """(tree_id, node_id): lower ends of the edges of a heaviest matching.

    A vertex in state M is matched to one child that is free; where several children are free any with the
    right gain would do, so the heaviest gain (edge weight plus free value against best value) is taken.
    """
    from .problems import matching

    ready = tree if isinstance(tree, Prepared) else prepare_tree(tree, m, seed)
    states = materialise(recover(ready, matching()), "matching")
    kids = original.where("parent_id IS NOT NULL").select("tree_id", "node_id", "parent_id", "edge_w")
    upper = states.where("state = 'M'").select("tree_id", F.col("node_id").alias("parent_id"))
    free = states.where("state = 'U'").select("tree_id", "node_id")
    values = vertex_pairs(ready)
    options = kids.join(upper, ["tree_id", "parent_id"]).join(free, ["tree_id", "node_id"]).join(values, ["tree_id", "node_id"])
    gain = F.col("edge_w") + F.col("free_value") - F.col("best_value")
    return options.groupBy("tree_id", "parent_id").agg(F.max_by("node_id", F.struct(gain, F.col("node_id"))).alias("node_id")).select("tree_id", "node_id")


def vertex_pairs(ready: Prepared) -> DataFrame:
    """(tree_id, node_id, best_value, free_value) of the matching problem."""
    from .finite import values_per_vertex
    from .problems import Problem, matching

    full = matching()
    free = Problem("free_matching", full.states, full.init, full.lift, full.join, ("U",))
    best = values_per_vertex(ready, full).withColumnRenamed("value", "best_value")
    return best.join(values_per_vertex(ready, free).withColumnRenamed("value", "free_value"), ["tree_id", "node_id"])
