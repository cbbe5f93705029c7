"""Solver for small-state problems: summarise each piece where it lies, then join the summaries.

A piece with up to two unknown leaves (roots of the pieces below it) is folded
once for each combination of their states; its summary is a small tensor
T[root state, state of leaf 1, state of leaf 2]. Pieces of a task are folded
together, level by level, on arrays. The summaries of a tree, about 14 m of
them, are then joined in one task, from the bottom up.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import NEG
from ..plans.decompose import Decomposition, Rules, Unchecked, decompose, default_machines, near_ids, positions
from ..plans.iterate import materialise, measured, prepare, release
from .binarize import SHAPES, binary_extension, default_cap, start
from .problems import EDGE, NODE, Problem

#: Most vertices a machine's share may have: a piece is folded in one task, states^3 numbers for each vertex.
MOST_SHARE = 200_000
PARTIAL = "tree_id long, comp_id long, leaf_comps array<long>, tensor array<long>"


# ---- array kernels ----


@dataclass
class Tables:
    """A problem's tables as index lists; weights are negated for minimisation."""

    problem: Problem

    def __post_init__(self):
        p = self.problem
        self.s = len(p.states)
        at = {name: i for i, name in enumerate(p.states)}
        self.sign = 1 if p.sense == "max" else -1
        self.init = [(at[k], *self._weight(v)) for k, v in p.init.items()]
        self.helper = [(at[k], *self._weight(v)) for k, v in p.helper_init.items()]
        self.lift = [(at[a], at[b], 1 if w == EDGE else 0) for a, b, w in p.lift]
        self.join = [(at[a], at[b], at[c]) for a, b, c in p.join]
        self.final = [at[x] for x in p.final]

    @staticmethod
    def _weight(v) -> tuple[int, int]:
        """(1 if the weight is the vertex's, factor)."""
        if v == NODE:
            return 1, 1
        if isinstance(v, tuple):
            return 1, v[1]
        return 0, int(v)

    def start(self, aux: np.ndarray, w: np.ndarray, width: int) -> np.ndarray:
        """[n, states, width]: vectors before any child."""
        out = np.full((len(w), self.s, width), NEG, np.int64)
        w = self.sign * (np.ones_like(w) if self.problem.unit else w)
        for rows, entries in ((~aux, self.init), (aux, self.helper)):
            for state, weighted, factor in entries:
                out[rows, state, :] = (factor * w[rows] if weighted else self.sign * factor * np.ones(rows.sum(), np.int64))[:, None]
        return out

    def lifted(self, child: np.ndarray, aux: np.ndarray, edge_w: np.ndarray) -> np.ndarray:
        """Vectors of children as their parents see them."""
        out = np.full_like(child, NEG)
        w = self.sign * (np.ones_like(edge_w) if self.problem.unit else edge_w)
        for a, b, weighted in self.lift:
            np.maximum(out[:, b], child[:, a] + (w[:, None] if weighted else 0), out=out[:, b])
        out[aux] = child[aux]
        return np.maximum(out, NEG)

    def joined(self, one: np.ndarray, two: np.ndarray) -> np.ndarray:
        out = np.full_like(one, NEG)
        for a, b, c in self.join:
            np.maximum(out[:, c], one[:, a] + two[:, b], out=out[:, c])
        return np.maximum(out, NEG)

    def best(self, vector: np.ndarray) -> int | None:
        v = max(int(vector[i]) for i in self.final)
        return None if v <= NEG // 2 else self.sign * v


def levels_of(parent: np.ndarray) -> np.ndarray:
    """Depth of every position below its root (-1 parents), by pointer doubling."""
    depth = (parent >= 0).astype(np.int64)
    ptr = parent.copy()
    while True:
        far = ptr >= 0
        if not far.any():
            return depth
        depth[far] += depth[ptr[far]]
        nxt = np.full_like(ptr, -1)
        nxt[far] = ptr[ptr[far]]
        ptr = nxt


def fold(tables: Tables, parent: np.ndarray, aux: np.ndarray, node_w: np.ndarray, edge_w: np.ndarray, fixed: np.ndarray, vectors: np.ndarray, width: int) -> np.ndarray:
    """Vectors of all positions, deepest level first. fixed positions keep the given vectors ([n_fixed, states, width])."""
    value = tables.start(aux, node_w, width)
    if len(fixed):
        value[fixed] = vectors
    depth = levels_of(parent)
    order = np.argsort(-depth, kind="stable")
    bounds = np.flatnonzero(np.diff(depth[order])) + 1
    for level in np.split(order, bounds):
        up = parent[level]
        level, up = level[up >= 0], up[up >= 0]
        if not len(level):
            continue
        seen = tables.lifted(value[level], aux[level], edge_w[level])
        # siblings go in one after the other: at most two in a binary tree, any number in general
        rest = np.argsort(up, kind="stable")
        while len(rest):
            first = np.ones(len(rest), bool)
            first[1:] = up[rest[1:]] != up[rest[:-1]]
            now = rest[first]
            value[up[now]] = tables.joined(value[up[now]], seen[now])
            rest = rest[~first]
    return value


def _scenarios(s: int, slot: np.ndarray, width: int) -> np.ndarray:
    """Unit vectors of unknown leaves: leaf in slot 0 is in state i // s of scenario i, in slot 1 in state i % s."""
    scenario = np.arange(width)
    state = np.where(slot[:, None] == 0, scenario // s, scenario % s)
    out = np.full((len(slot), s, width), NEG, np.int64)
    np.put_along_axis(out, state[:, None, :], 0, axis=1)
    return out


# ---- pieces ----


def piece_rows(bt: DataFrame, dec: Decomposition) -> DataFrame:
    """Vertices with their piece, and the root of every lower piece once more as a leaf of the piece above it."""
    own = bt.join(dec.assign, ["tree_id", "node_id"])
    above = dec.comp.where("parent_comp IS NOT NULL").select("tree_id", F.col("comp_id").alias("node_id"), F.col("comp_id").alias("leaf"), F.col("parent_comp").alias("comp_id"))
    leaves = bt.join(F.broadcast(above) if dec.few else above, ["tree_id", "node_id"])
    columns = ["tree_id", "comp_id", "node_id", "parent_id", "is_aux", "origin_id", "node_w", "edge_w", "leaf"]
    return own.withColumn("leaf", F.lit(None).cast("long")).select(*columns).unionAll(leaves.select(*columns))


def _sorted_runs(batches: Iterator[pa.RecordBatch], keys: list[str], rows: int = 200_000) -> Iterator[pa.Table]:
    """Tables of whole runs of the keys, from sorted input, at least `rows` long where possible."""
    held: list[pa.RecordBatch] = []
    count = 0
    for batch in batches:
        if not batch.num_rows:
            continue
        if count >= rows:
            cols = [batch.column(k).to_numpy(zero_copy_only=False) for k in keys]
            last = [held[-1].column(k)[held[-1].num_rows - 1].as_py() for k in keys]
            same = np.ones(batch.num_rows, bool)
            for c, v in zip(cols, last):
                same &= c == v
            cut = batch.num_rows if same.all() else int(np.argmin(same))
            held.append(batch.slice(0, cut))
            if cut < batch.num_rows:
                yield pa.Table.from_batches(held).combine_chunks()
                held, count = [batch.slice(cut)], batch.num_rows - cut
            continue
        held.append(batch)
        count += batch.num_rows
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def _piece_arrays(table: pa.Table):
    tree, comp = table["tree_id"].to_numpy(), table["comp_id"].to_numpy()
    node, above = table["node_id"].to_numpy(), table["parent_id"].fill_null(-1).to_numpy()
    _, code = np.unique(np.stack([tree, comp], 1), axis=0, return_inverse=True)
    code = code.reshape(-1)
    order = np.lexsort((node, code))
    code, node, above = code[order], node[order], above[order]
    take = lambda name, fill: table[name].fill_null(fill).to_numpy()[order]
    aux = np.asarray(table["is_aux"].to_numpy(zero_copy_only=False), bool)[order]
    parent = positions(code, node, above)
    return tree[order], comp[order], node, parent, aux, take("node_w", 0), take("edge_w", 0), take("leaf", -1), code, order


def _slots(code: np.ndarray, leaf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions of unknown leaves and their slot in their piece, by id."""
    at = np.flatnonzero(leaf >= 0)
    slot = np.zeros(len(at), np.int64)
    slot[1:] = code[at[1:]] == code[at[:-1]]
    return at, slot


def _compress(problem: Problem):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = Tables(problem)
        for table in _sorted_runs(batches, ["tree_id", "comp_id"]):
            tree, comp, node, parent, aux, node_w, edge_w, leaf, code, _ = _piece_arrays(table)
            at, slot = _slots(code, leaf)
            width = tables.s**2 if len(at) else 1
            value = fold(tables, parent, aux, node_w, edge_w, at, _scenarios(tables.s, slot, width) if len(at) else np.zeros((0, tables.s, 1), np.int64), width)
            roots = np.flatnonzero((node == comp) & (leaf < 0))
            leaves: list[list[int]] = [[] for _ in roots]
            place = {int(code[r]): i for i, r in enumerate(roots)}
            for a in at.tolist():
                leaves[place[int(code[a])]].append(int(leaf[a]))
            flat = value[roots].reshape(len(roots), -1)
            tensor = pa.ListArray.from_arrays(pa.array(np.arange(len(roots) + 1, dtype=np.int32) * flat.shape[1]), pa.array(flat.reshape(-1)))
            yield pa.RecordBatch.from_arrays([pa.array(tree[roots]), pa.array(comp[roots]), pa.array(leaves, pa.list_(pa.int64())), tensor], ["tree_id", "comp_id", "leaf_comps", "tensor"])

    return run


def compress(bt: DataFrame, dec: Decomposition, problem: Problem) -> DataFrame:
    """PARTIAL: the summary tensor of every piece. A piece fits one task by construction; tasks take many pieces."""
    prepare(bt.sparkSession)
    rows = piece_rows(bt, dec).select("tree_id", "comp_id", "node_id", "parent_id", "is_aux", "node_w", "edge_w", "leaf")
    return rows.repartition("tree_id", "comp_id").sortWithinPartitions("tree_id", "comp_id").mapInArrow(_compress(problem), PARTIAL)


def evaluate(tensor: np.ndarray, leaf_vectors: list[np.ndarray], s: int) -> np.ndarray:
    """Root vector of a piece whose leaves are now known."""
    t = np.asarray(tensor, np.int64).reshape(s, -1)
    if not leaf_vectors:
        return t[:, 0]
    t = t.reshape(s, s, s)
    a = leaf_vectors[0]
    with_first = np.maximum(t + a[None, :, None], NEG).max(axis=1)
    if len(leaf_vectors) == 1:
        return with_first[:, 0]
    return np.maximum(with_first + leaf_vectors[1][None, :], NEG).max(axis=1)


def merge(child: np.ndarray, parent: np.ndarray, slot: int, s: int) -> np.ndarray:
    """Summary of two touching pieces: the child's root state meets the parent's leaf `slot`.

    child is [s, s] (one leaf of its own at most), the result [s, s, s] has the child's leaf in that slot.
    """
    c = np.asarray(child, np.int64).reshape(s, s)
    p = np.asarray(parent, np.int64).reshape(s, s, s)
    if slot == 0:
        return np.maximum(p[:, :, None, :] + c[None, :, :, None], NEG).max(axis=1)
    return np.maximum(p[:, :, :, None] + c[None, None, :, :], NEG).max(axis=2)


def _finish(problem: Problem, vectors: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = Tables(problem)
        for table in _sorted_runs(batches, ["tree_id"]):
            rows = table.to_pylist()
            at = {(r["tree_id"], r["comp_id"]): r for r in rows}
            done: dict[tuple[int, int], np.ndarray] = {}
            below = {(t, c) for (t, _), r in at.items() for c in r["leaf_comps"]}
            for key in (k for k in at if k not in below):
                stack = [key]
                while stack:
                    top = stack[-1]
                    kids = [(top[0], c) for c in at[top]["leaf_comps"]]
                    open_ = [k for k in kids if k not in done]
                    if open_:
                        stack += open_
                        continue
                    done[top] = evaluate(at[top]["tensor"], [done[k] for k in kids], tables.s)
                    stack.pop()
            if vectors:
                keys = list(done)
                yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys], pa.int64()), pa.array([k[1] for k in keys], pa.int64()), pa.array([done[k].tolist() for k in keys], pa.list_(pa.int64()))], ["tree_id", "comp_id", "vector"])
            else:
                roots = [k for k in at if k not in below]
                values = [tables.best(done[k]) for k in roots]
                n = len(roots)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([k[0] for k in roots], pa.int64()), pa.array([problem.name] * n), pa.nulls(n, pa.int64()), pa.array(values, pa.int64()), pa.array([v is not None for v in values])],
                    ["tree_id", "problem", "param", "value", "feasible"],
                )

    return run


def finish(partial: DataFrame, problem: Problem) -> DataFrame:
    """ANSWER of every tree: its summaries meet in one task and are joined from the lowest pieces up."""
    prepare(partial.sparkSession)
    return partial.repartition("tree_id").sortWithinPartitions("tree_id").mapInArrow(_finish(problem, False), "tree_id long, problem string, param long, value long, feasible boolean")


@dataclass
class Prepared:
    """A tree made ready once for any number of problems: binary extension and decomposition."""

    bt: DataFrame
    dec: Decomposition


def prepare_tree(tree: DataFrame, m: int | None = None, seed: int = 0, shape: str = "balanced", rules: Rules = Rules(), local_rows: int | None = None, cap: int | None = -1) -> Prepared:
    """m: number of machines; more are taken where their shares would pass MOST_SHARE vertices."""
    rows, seen = measured(start(tree), "tagged", n=F.count(F.lit(1)), roots=F.count_if(F.col("parent_id").isNull()), first=F.min("tree_id"), last=F.max("tree_id"), **near_ids())
    n = seen["n"]
    m = max(m or default_machines(n), -(-n // MOST_SHARE))
    bt = rows.drop("child_ord")
    if shape in SHAPES and seen["roots"] == 1 and seen["first"] == seen["last"]:
        try:
            return Prepared(bt, decompose(bt, m, seed, rules, local_rows, known=seen))
        except Unchecked:
            pass
    most = rows.where("parent_id IS NOT NULL").groupBy("tree_id", "parent_id").agg(F.count(F.lit(1)).alias("k")).agg(F.coalesce(F.max("k"), F.lit(0))).first()[0]
    # a tree of at most two children each is binary as it is
    if most > 2 or shape not in SHAPES:
        bt = materialise(binary_extension(tree, default_cap(n, m) if cap == -1 else cap, seed, shape, rows), "binary")
        release(rows)
    return Prepared(bt, decompose(bt, m, seed, rules, local_rows))


def solve(tree: DataFrame | Prepared, problem: Problem, m: int | None = None, seed: int = 0, shape: str = "balanced", finish_by: str = "master", **options) -> DataFrame:
    """ANSWER of every tree of the forest. finish_by 'master' joins all summaries of a tree at once, 'scheduled' in a logarithmic number of merge steps."""
    ready = tree if isinstance(tree, Prepared) else prepare_tree(tree, m, seed, shape, **options)
    partial = compress(ready.bt, ready.dec, problem)
    if finish_by == "scheduled":
        from .scheduled import finish_scheduled

        return finish_scheduled(materialise(partial, "partial"), ready.dec.comp, problem)
    return finish(partial, problem)


def piece_vectors(ready: Prepared, problem: Problem) -> DataFrame:
    """(tree_id, comp_id, vector): the finished vector of every piece's root."""
    partial = compress(ready.bt, ready.dec, problem)
    return partial.repartition("tree_id").sortWithinPartitions("tree_id").mapInArrow(_finish(problem, True), "tree_id long, comp_id long, vector array<long>")


def _values(problem: Problem):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = Tables(problem)
        for table in _sorted_runs(batches, ["tree_id", "comp_id"]):
            tree, comp, node, parent, aux, node_w, edge_w, leaf, code, order = _piece_arrays(table)
            at, _ = _slots(code, leaf)
            known = table["vector"].to_pylist()
            vectors = np.array([known[int(order[a])] for a in at], np.int64).reshape(-1, tables.s, 1)
            value = fold(tables, parent, aux, node_w, edge_w, at, vectors, 1)[:, :, 0]
            keep = np.flatnonzero(~aux & (leaf < 0))
            best = value[keep][:, tables.final].max(axis=1)
            mask = best <= NEG // 2
            yield pa.RecordBatch.from_arrays([pa.array(tree[keep]), pa.array(node[keep] >> 2), pa.array(tables.sign * best, mask=mask)], ["tree_id", "node_id", "value"])

    return run


def values_per_vertex(tree: DataFrame | Prepared, problem: Problem, m: int | None = None, seed: int = 0) -> DataFrame:
    """(tree_id, node_id, value): the answer of the subtree of every original vertex, by one more pass over the pieces."""
    ready = tree if isinstance(tree, Prepared) else prepare_tree(tree, m, seed)
    vectors = materialise(piece_vectors(ready, problem), "vectors").select("tree_id", F.col("comp_id").alias("leaf"), "vector")
    rows = piece_rows(ready.bt, ready.dec).select("tree_id", "comp_id", "node_id", "parent_id", "is_aux", "node_w", "edge_w", "leaf")
    joined = rows.where("leaf IS NULL").withColumn("vector", F.lit(None).cast("array<bigint>")).unionByName(rows.where("leaf IS NOT NULL").join(vectors, ["tree_id", "leaf"]))
    return joined.repartition("tree_id", "comp_id").sortWithinPartitions("tree_id", "comp_id").mapInArrow(_values(problem), "tree_id long, node_id long, value long")
