"""Vectors of cut problems as runs of equal cost, and their merges on a grid of blocks of runs.

A vector over millions of counts that has few different costs is a short list of
runs (lo, hi, cost), disjoint and ascending. A block holds the runs of one stretch
of counts; a pair of blocks gives the sums of their runs, and the owner of a
stretch keeps the least cost at each count.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

Runs = tuple[np.ndarray, np.ndarray, np.ndarray]
#: Most sums of runs that are held at once.
SUMS = 1 << 21


def least(lo: np.ndarray, hi: np.ndarray, cost: np.ndarray) -> Runs:
    """Runs of the least cost at every count that some of the given ones, which may overlap, reach.

    Counts between the ends of runs go together. A run covers two stretches whose lengths are the same power of two; longer
    stretches give their least cost to the two halves, so all runs of a power go at once.
    """
    if not len(lo):
        return lo, hi, cost
    ends = np.unique(np.r_[lo, hi + 1])
    a, b = np.searchsorted(ends, lo), np.searchsorted(ends, hi + 1)
    power = np.frexp((b - a).astype(np.float64))[1] - 1
    by_power = np.argsort(power, kind="stable")
    begins = np.searchsorted(power[by_power], np.arange(power.max() + 2))
    none = np.iinfo(np.int64).max
    now = np.full(len(ends) - 1, none)
    for k in range(len(begins) - 2, -1, -1):
        wide = 1 << k
        if 2 * wide <= len(now):
            np.minimum(now[wide:], now[:-wide].copy(), out=now[wide:])
        own = by_power[begins[k] : begins[k + 1]]
        np.minimum.at(now, a[own], cost[own])
        np.minimum.at(now, b[own] - wide, cost[own])
    first = np.flatnonzero(np.r_[True, now[1:] != now[:-1]])
    lo, hi, cost = ends[first], np.r_[ends[first[1:]], ends[-1]] - 1, now[first]
    held = cost < none
    return lo[held], hi[held], cost[held]


def sums(p: Runs, q: Runs, w: int, most: int, cap: int) -> Runs:
    """(min,+) convolution of runs, w added; counts above most and costs above cap are left out."""
    if len(p[0]) < len(q[0]):
        p, q = q, p
    got = tuple(np.zeros(0, np.int64) for _ in range(3))
    step = max(1, SUMS // max(1, len(p[0])))
    by_cost = np.argsort(q[2], kind="stable")
    for at in range(0, len(by_cost), step):
        part = by_cost[at : at + step]
        lo, cost = (np.add.outer(q[i][part], p[i]).ravel() for i in (0, 2))
        keep = (lo <= most) & (cost + w <= cap)
        hi = np.minimum(np.add.outer(q[1][part], p[1]).ravel()[keep], most)
        got = least(*(np.r_[x, y] for x, y in zip(got, (lo[keep], hi, cost[keep] + w))))
    return got


def fold_piece(up: dict[int, int], size: dict[int, int], weight: dict[int, int], most: int, cap: int, helpers: frozenset[int] = frozenset(), ends: frozenset[int] = frozenset(), work: float = np.inf) -> tuple[list[int], dict[int, Runs]] | None:
    """Border and profile by labelling of it, of one small tree in order, each vertex counting for its size. None: more than `work` sums of runs.

    ends: vertices whose labels stay, as edges cut before end there. helpers carry the label of the vertex above.
    """
    kids: dict[int, list[int]] = {}
    for v, p in up.items():
        kids.setdefault(p, []).append(v)
    order = [next(v for v in size if v not in up)]
    for v in order:
        order += kids.get(v, [])
    below_all = dict(size)
    for v in reversed(order[1:]):
        below_all[up[v]] += below_all[v]
    tables: dict[int, tuple[list[int], dict[int, Runs]]] = {}
    for v in reversed(order):
        # a vertex comes first in its border
        border, mine = [v], {x: tuple(np.array([s]) for s in (x * size[v], x * size[v], 0)) for x in (0, 1)}
        # small ones first: their counts lie close together, so runs stay few
        for c in sorted(kids.get(v, []), key=below_all.get):
            c_border, low = tables.pop(c)
            seen: dict[tuple[int, int], list[Runs]] = {}
            for colour, (lo, hi, cost) in low.items():
                for x in (0, 1):
                    if x == colour & 1:
                        seen.setdefault((x, colour if c in ends else colour >> 1), []).append((lo, hi, cost))
                    elif c not in helpers:
                        seen.setdefault((x, colour if c in ends else colour >> 1), []).append((lo, hi, cost + weight[c]))
            below = {key: least(*(np.concatenate(x) for x in zip(*some))) for key, some in seen.items()}
            pairs = [(p, x, rest) for p in mine for x, rest in below if p & 1 == x]
            work -= sum(len(mine[p][0]) * len(below[x, rest][0]) for p, x, rest in pairs)
            if work < 0:
                return None
            mine = {p | rest << len(border): sums(mine[p], below[x, rest], 0, most, cap) for p, x, rest in pairs}
            border += c_border if c in ends else c_border[1:]
        tables[v] = border, mine
    border, mine = tables[order[0]]
    if order[0] in ends:
        return border, mine
    both = {rest: [mine[p] for p in mine if p >> 1 == rest] for rest in {p >> 1 for p in mine}}
    return border[1:], {rest: least(*(np.concatenate(x) for x in zip(*some))) for rest, some in both.items()}


def fold(up: dict[int, int], size: dict[int, int], weight: dict[int, int], most: int, cap: int, work: float = np.inf) -> Runs | None:
    """Profile of one small tree in order; the sequential form. None: more than `work` sums of runs."""
    got = fold_piece(up, size, weight, most, cap, work=work)
    return None if got is None else got[1][0]


def _rows(keys: list[list], runs: list[Runs], length: int) -> pa.RecordBatch:
    """VECBLK rows whose vals are the los, his and costs of the runs inside a stretch of `length` counts."""
    out: list[list] = [[] for _ in range(6)]
    for *key, (lo, hi, cost) in zip(*keys, runs):
        for no in range(int(lo[0]) // length, int(hi[-1]) // length + 1) if len(lo) else ():
            a, b = np.searchsorted(hi, no * length), np.searchsorted(lo, (no + 1) * length)
            if a == b:
                continue
            inside = np.r_[np.maximum(lo[a:b], no * length), np.minimum(hi[a:b], (no + 1) * length - 1), cost[a:b]]
            for column, value in zip(out, (*key, no * length, inside)):
                column.append(value)
    types = [pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.int32(), pa.int64(), pa.list_(pa.int64())]
    return pa.RecordBatch.from_arrays([pa.array(r, t) for r, t in zip(out, types)], ["tree_id", "part_id", "border", "colour", "start", "vals"])


def _split(vals) -> Runs:
    return tuple(np.asarray(vals, np.int64).reshape(3, -1))


def joined(blocks) -> Runs:
    """Least cost over all labellings, from the vals of blocks."""
    return least(*(np.concatenate(x) for x in zip(*map(_split, blocks))))


def at(runs: Runs, count: int) -> int | None:
    """Cost at a count."""
    lo, hi, cost = runs
    i = int(np.searchsorted(hi, count))
    return int(cost[i]) if i < len(lo) and lo[i] <= count else None


def pairs_of_runs(most: int, cap: int, length: int):
    """What pairs of blocks of runs give (cuts, least cost), a row for each stretch of the result."""
    from .linear import joint_border, project

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys: list[list] = [[], [], [], []]
            made: list[Runs] = []
            for r in batch.to_pylist():
                x = r["p_colour"] >> r["p_border"].index(r["upper_end"]) & 1
                y = r["q_colour"] >> r["q_border"].index(r["lower_end"]) & 1
                if r["helper"] and x != y:
                    continue
                border = joint_border(r["p_border"], r["q_border"], set(r["closed"]))
                colour = project(r["p_colour"], r["p_border"], border) | project(r["q_colour"], r["q_border"], border)
                for column, value in zip(keys, (r["tree_id"], r["out_part"], border, colour)):
                    column.append(value)
                made.append(sums(_split(r["p_vals"]), _split(r["q_vals"]), r["w"] if x != y and not r["helper"] else 0, most, cap))
            yield _rows(keys, made, length)

    return run


def unify_runs(pairs: DataFrame, length: int, schema: str) -> DataFrame:
    """The owner of a stretch of counts keeps the least cost at each."""

    def run(table: pa.Table) -> pa.Table:
        lo, hi, cost = (np.concatenate(x) for x in zip(*[_split(v) for v in table["vals"].to_pylist()]))
        keys = [[table[c][0].as_py()] for c in ("tree_id", "part_id", "border", "colour")]
        return pa.Table.from_batches([_rows(keys, [least(lo, hi, cost)], length)])

    return pairs.groupBy("tree_id", "part_id", "border", "colour", "start").applyInArrow(run, schema)


def pieces_of_runs(most: int, cap: int, length: int):
    """VECBLK rows of pieces, each given by its vertices and folded in order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                node, inside = r["node"], set(r["node"])
                up = {v: p for v, p in zip(node, r["up"]) if p in inside}
                helpers = frozenset(v for v, a in zip(node, r["aux"]) if a)
                border, table = fold_piece(up, dict(zip(node, r["size"])), dict(zip(node, r["weight"])), most, cap, helpers, frozenset(r["ends"]))
                k = len(table)
                yield _rows([[r["tree_id"]] * k, [r["part_id"]] * k, [border] * k, list(table)], list(table.values()), length)

    return run
