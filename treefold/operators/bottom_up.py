"""Problems for which only the plain bottom-up form is built: one tree in one task.

Right for any tree; no bound on rounds is claimed. k-median, facility location and
least diameter refuse trees above MAX_VERTICES, as they hold tables that grow with
the square of the tree; the others take trees of any size that one task can hold.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .baselines import ANSWER, _answer_batch, tree_arrays
from .finite import levels_of
from .linear import BISECTION, INF, K_MAX, K_MIN, convolve, fold_piece

MAX_VERTICES = 5_000


def _order(parent: np.ndarray) -> list[int]:
    """Children before parents."""
    kids: list[list[int]] = [[] for _ in parent]
    roots = []
    for v, p in enumerate(parent.tolist()):
        (kids[p] if p >= 0 else roots).append(v)
    order = roots
    for v in order:
        order += kids[v]
    return order[::-1]


def distances(parent: np.ndarray, edge_w: np.ndarray) -> np.ndarray:
    """All distances of one tree, a row at a time from parents to children."""
    n = len(parent)
    d = np.zeros((n, n), np.int64)
    seen: list[int] = []
    for v in reversed(_order(parent)):
        p = parent[v]
        if p >= 0:
            d[v, seen] = d[p, seen] + edge_w[v]
            d[seen, v] = d[v, seen]
        seen.append(v)
    return d


def _per_tree(tree: DataFrame, name: str, param: int | None, solve: Callable[[np.ndarray, np.ndarray, np.ndarray], int | None], most: int | None = None) -> DataFrame:
    def run(table: pa.Table) -> pa.Table:
        if most is not None and table.num_rows > most:
            raise ValueError(f"a tree of {table.num_rows} vertices is above the limit of the bottom-up form")
        trees, _, parent, node_w, edge_w = tree_arrays(table)
        return pa.Table.from_batches([_answer_batch([int(trees[0])], name, [solve(parent, node_w, edge_w)], [param])])

    return tree.select("tree_id", "node_id", "parent_id", "node_w", "edge_w").groupBy("tree_id").applyInArrow(run, ANSWER)


def _vector(problem, parent, edge_w) -> np.ndarray:
    n = len(parent)
    root = int(np.flatnonzero(parent < 0)[0])
    up = {v: (int(parent[v]) if parent[v] >= 0 else -1) for v in range(n)}
    table = fold_piece(problem, list(range(n)), {v: p for v, p in up.items() if v != root}, {v: False for v in range(n)}, dict(enumerate(edge_w.tolist())), {})
    return np.minimum.reduce(list(table.table.values()))


def bisection_sequential(tree: DataFrame) -> DataFrame:
    """The quadratic table of the whole tree on one machine."""

    def solve(parent, node_w, edge_w):
        v = _vector(BISECTION, parent, edge_w)[len(parent) // 2]
        return None if v >= INF // 2 else int(v)

    return _per_tree(tree, BISECTION.name, None, solve)


def least_span(parent: np.ndarray, edge_w: np.ndarray, k: int) -> int:
    """Least weight of k >= 2 connected vertices, on arrays of k + 1 numbers for each vertex.

    held[v, j]: j vertices below v, v among them. All vertices of a level go at once; a tree
    with few vertices on a level (as a path has) goes vertex by vertex.
    """
    n = len(parent)
    depth = levels_of(parent)
    if int(depth.max()) * 20 > n:
        up = dict(enumerate(parent.tolist()))
        table = fold_piece(K_MIN, list(range(n)), {v: p for v, p in up.items() if p >= 0}, dict.fromkeys(range(n), False), dict(enumerate(edge_w.tolist())), {}, k)
        return int(min(v[k] for v in table.table.values()))
    held = np.full((n, k + 1), INF, np.int64)
    held[:, 1] = 0
    order = np.argsort(-depth, kind="stable")
    for level in np.split(order, np.flatnonzero(np.diff(depth[order])) + 1):
        level = level[parent[level] >= 0]
        rest = level[np.argsort(parent[level], kind="stable")]
        # siblings go in one after the other
        while len(rest):
            up = parent[rest]
            first = np.ones(len(rest), bool)
            first[1:] = up[1:] != up[:-1]
            now, above = rest[first], up[first]
            mine, seen = held[above], held[now] + edge_w[now, None]
            out = mine.copy()
            for j in range(1, k):
                np.minimum(out[:, j + 1 :], mine[:, 1 : k + 1 - j] + seen[:, j, None], out=out[:, j + 1 :])
            held[above] = np.minimum(out, INF)
            rest = rest[~first]
    return int(held[:, k].min())


def k_spanning_sequential(tree: DataFrame, k: int, sense: str = "min") -> DataFrame:
    problem = K_MIN if sense == "min" else K_MAX

    sign = 1 if sense == "min" else -1

    def solve(parent, node_w, edge_w):
        if not 0 <= k <= len(parent):
            return None
        if k < 2:
            return 0
        v = least_span(parent, sign * edge_w, k)
        return None if v >= INF // 2 else v * sign

    return _per_tree(tree, problem.name, k, solve)


def centres_needed(parent: list[int], edge_w: list[int], r: int, order: list[int]) -> int:
    """Fewest centres so that every vertex has one within distance r: a centre goes as high as the farthest vertex below allows."""
    n = len(parent)
    far = [-1] * n  # farthest unserved vertex below, -1: none
    near = [int(INF)] * n  # nearest centre below
    placed = 0
    for v in order:
        f, c, p, w = far[v], near[v], parent[v], edge_w[v]
        if c > r and f < 0:
            f = 0
        if f >= 0 and c + f <= r:
            f = -1
        if f >= 0 and (p < 0 or f + w > r):
            placed += 1
            c, f = 0, -1
        if p >= 0:
            if f >= 0:
                far[p] = max(far[p], f + w)
            near[p] = min(near[p], c + w)
    return placed


def k_center(tree: DataFrame, k: int) -> DataFrame:
    """Least radius within which k vertices serve all: weights are whole numbers, so a binary search over radii finds it."""

    def solve(parent, node_w, edge_w):
        if k < 1:
            return None
        order = _order(parent)
        up, weight = parent.tolist(), edge_w.tolist()
        low, high = 0, sum(w for w, p in zip(weight, up) if p >= 0)
        while low < high:
            middle = (low + high) // 2
            if centres_needed(up, weight, middle, order) <= k:
                high = middle
            else:
                low = middle + 1
        return low

    return _per_tree(tree, "k_center", k, solve)


def facility_location(tree: DataFrame) -> DataFrame:
    """Opening costs (vertex weights) plus every vertex's distance to its open vertex, least.

    cost[v, u]: the subtree of v when v is served by u, with u's opening cost in it. A child is served
    by u too (whose cost is then counted once) or by a vertex of its own subtree.
    """

    def solve(parent, node_w, edge_w):
        d = distances(parent, edge_w)
        n = len(parent)
        cost = d + node_w[None, :]
        inside = np.eye(n, dtype=bool)
        for v in _order(parent):
            p = parent[v]
            if p >= 0:
                own = cost[v][inside[v]].min()
                cost[p] += np.minimum(cost[v] - node_w, own)
                inside[p] |= inside[v]
            else:
                return int(cost[v].min())

    return _per_tree(tree, "facility_location", None, solve, MAX_VERTICES)


def k_median(tree: DataFrame, k: int) -> DataFrame:
    """Least sum of distances to k chosen vertices (at most k)."""

    def solve(parent, node_w, edge_w):
        d = distances(parent, edge_w)
        n = len(parent)
        if k < 1:
            return None
        most = min(k, n)
        # cost[v][u, j]: subtree of v, v served by u, j centres counted, u among them
        cost = np.full((n, n, most + 1), INF, np.int64)
        cost[:, :, 1] = d
        inside = np.eye(n, dtype=bool)
        for v in _order(parent):
            p = parent[v]
            if p < 0:
                return int(cost[v].min())
            own = cost[v][inside[v]].min(axis=0)
            shared = np.full((n, most + 1), INF, np.int64)
            shared[:, :most] = cost[v][:, 1:]
            child = np.minimum(shared, own[None, :])
            out = np.full((n, most + 1), INF, np.int64)
            for i in range(1, most + 1):
                for j in range(most + 1 - i):
                    out[:, i + j] = np.minimum(out[:, i + j], cost[p][:, i] + child[:, j])
            cost[p] = np.minimum(out, INF)
            inside[p] |= inside[v]

    return _per_tree(tree, "k_median", k, solve, MAX_VERTICES)


def minimum_diameter(tree: DataFrame, k: int) -> DataFrame:
    """Least diameter of a connected set of k vertices (read so; the source does not define it).

    The ball around the middle of a path of length D holds every connected set of diameter D on it.
    """

    def solve(parent, node_w, edge_w):
        d = distances(parent, edge_w)
        n = len(parent)
        if not 1 <= k <= n:
            return None
        if k == 1:
            return 0
        best = None
        for x in range(n):
            reach = np.maximum(d[x][None, :], d)  # farther of x and y, for each y and z
            held = (reach <= d[x][:, None]).sum(axis=1)
            good = d[x][held >= k]
            if len(good):
                best = int(good.min()) if best is None else min(best, int(good.min()))
        return best

    return _per_tree(tree, "minimum_diameter", k, solve, MAX_VERTICES)


def k_partition(tree: DataFrame, cap: int) -> DataFrame:
    """Fewest connected parts of at most cap vertices (read so; the source does not define it).

    cuts[v][s]: cut edges below v when v's own part has s vertices.
    """

    def solve(parent, node_w, edge_w):
        if cap < 1:
            return None
        cuts = {}
        for v in _order(parent):
            mine = cuts.pop(v, None)
            if mine is None:
                mine = np.array([INF, 0], np.int64)
            p = parent[v]
            if p < 0:
                return int(mine.min()) + 1
            closed = np.array([int(mine.min()) + 1], np.int64)
            above = cuts.get(p, np.array([INF, 0], np.int64))
            kept = convolve(above, mine)[: cap + 1]
            cut = convolve(above, closed)
            out = np.full(max(len(kept), len(cut)), INF, np.int64)
            out[: len(kept)] = kept
            np.minimum(out[: len(cut)], cut, out=out[: len(cut)])
            cuts[p] = out

    return _per_tree(tree, "k_partition", cap, solve)
