"""Solver for problems whose tables grow with the subtree: minimum bisection and k-vertex spanning subtrees.

Every vertex has a label bit (blue, or inside the subtree). A part (a connected
set of pieces) holds, for each labelling of the ends of its cut edges, the
vector of best costs by the number of original vertices labelled 1. Two parts
are merged over one edge by a (min,+) convolution; helpers carry their parent's
label and are not counted.

Vectors are rows of blocks. A merge is a join of the blocks of its two sides on
the part they form, so every pair of blocks is its own row of work; each result
element is then the minimum over the pairs that reach it. Merges follow the
schedule, so their turns are logarithmic in the number of pieces.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import TREE
from ..plans import schedule as plan
from ..plans.decompose import Rules, contract_arrays, positions
from ..plans.iterate import materialise, prepare, release
from ..plans.rake import closest, largest, rake
from . import runs
from .finite import MOST_SHARE, Prepared, _sorted_runs, piece_rows, prepare_tree

INF = 1 << 60
#: Vectors of at most so many elements in all are merged in one task for each tree.
LOCAL_FLOOR = 20_000
#: Rows whose spans are computed at once, and most numbers held for that where vertices have two children.
SPAN_ROWS, SPAN_NUMBERS = 200_000, 1 << 24
#: Trees of so many vertices are bisected over their lightest edges first: so many of them, and then more.
LIGHT_FROM, LIGHT_EDGES = 50_000, (64, 256, 1024)
#: Where light edges alone reach no half: edges are ranked by their subtree's size to their weight. So many are looked at, so many
#: are cut at most; the first costs tried, over FIRST_EDGES (more where these reach no half) and those of weight 0, with so many sums of runs at most.
RANKED_EDGES, CUT_EDGES, FIRST_EDGES, FIRST_CAPS, FIRST_SUMS = 4096, 512, 32, (8, 32, 128, 512, 2048), 1 << 29
#: Vectors of more possible indexes than DENSE are convolved by their values, where there are at most so many pairs of these.
DENSE, VALUE_PAIRS = 2_000, 64
VECBLK = "tree_id long, part_id long, border array<long>, colour int, start long, vals array<long>"


@dataclass(frozen=True)
class VectorProblem:
    """kind 'cut': cost of edges whose ends differ. kind 'span': weight of edges inside one connected set of 1s.

    cap: for cuts, costs above it are not asked for.
    """

    name: str
    kind: str
    sense: str = "min"
    cap: int | None = None


BISECTION = VectorProblem("minimum_bisection", "cut")
K_MIN = VectorProblem("minimum_k_spanning_tree", "span", "min")
K_MAX = VectorProblem("maximum_k_spanning_tree", "span", "max")


def _by_values(a: np.ndarray, b: np.ndarray, size: int) -> np.ndarray | None:
    """(min,+) convolution of vectors of few different values: one convolution of indicators for each sum. None: too many values."""
    xs, ys = (np.unique(v[v < INF]) for v in (a, b))
    if len(xs) * len(ys) > VALUE_PAIRS:
        return None
    width = 1 << (len(a) + len(b) - 2).bit_length()
    one, two = ([np.fft.rfft(v == x, width) for x in values] for v, values in ((a, xs), (b, ys)))
    sums: dict[int, np.ndarray] = {}
    for x, f in zip(xs.tolist(), one):
        for y, g in zip(ys.tolist(), two):
            sums[x + y] = sums[x + y] + f * g if x + y in sums else f * g
    out = np.full(size, INF, np.int64)
    for total in sorted(sums, reverse=True):
        # counts of pairs, far apart from zero against the error of the transform
        out[np.fft.irfft(sums.pop(total), width)[:size] > 0.5] = total
    return out


def convolve(a: np.ndarray, b: np.ndarray, most: int | None = None) -> np.ndarray:
    """(min,+) convolution of two vectors, the one with fewer possible indexes looped over; of most elements at most."""
    size = len(a) + len(b) - 1
    if most is not None:
        size = min(size, most)
    a, b = a[:size], b[:size]
    if np.count_nonzero(a < INF) < np.count_nonzero(b < INF):
        a, b = b, a
    at = np.flatnonzero(b < INF)
    if len(at) > DENSE and (out := _by_values(a, b, size)) is not None:
        return out
    out = np.full(size, INF, np.int64)
    for i, v in zip(at.tolist(), b[at].tolist()):
        part = out[i : i + len(a)]
        np.minimum(part, a[: len(part)] + v, out=part)
    return np.minimum(out, INF)


def pair(problem: VectorProblem, p: np.ndarray, p_start: int, p_colour: int, x: int, q: np.ndarray, q_start: int, q_colour: int, y: int, w: int, helper: bool, most: int | None = None) -> tuple[int, np.ndarray] | None:
    """What two blocks give over an edge whose ends have labels x (upper) and y (lower): (start, vector), or nothing.

    most: only so many vertices labelled 1 are asked for, so longer vectors are cut.

    The vector has at most |P| + |Q| elements and each reaches one element of the result.
    """
    if helper and x != y:
        return None
    room = None if most is None else most + 1 - p_start - q_start
    if problem.kind == "cut":
        if room is not None and room < 1:
            return None
        out = np.minimum(convolve(p, q, room) + (w if x != y and not helper else 0), INF)
        if problem.cap is not None:
            out[out > problem.cap] = INF
        return p_start + q_start, out
    if x and y:
        if room is not None and room < 1:
            return None
        return p_start + q_start, np.minimum(convolve(p, q, room) + (0 if helper else w), INF)
    # at most one side may hold a vertex of the set
    out = None
    if q_colour == 0 and q_start == 0 and q[0] < INF:
        out = (p_start, np.minimum(p + q[0], INF))
    if p_colour == 0 and p_start == 0 and p[0] < INF:
        other = (q_start, np.minimum(q + p[0], INF))
        if out is None:
            out = other
        else:
            start = min(out[0], other[0])
            length = max(out[0] + len(out[1]), other[0] + len(other[1])) - start
            both = np.full(length, INF, np.int64)
            for s, v in (out, other):
                np.minimum(both[s - start : s - start + len(v)], v, out=both[s - start : s - start + len(v)])
            out = (start, both)
    return out


def _vertex(size: int, most: int | None = None) -> dict[int, np.ndarray]:
    """A single vertex that is its own border: label 0 or 1. size: how many vertices it counts for (a helper: 0)."""
    out = {x: np.full(size + 1, INF, np.int64) for x in (0, 1)}
    out[0][0] = out[1][size] = 0
    return {x: v[: None if most is None else most + 1] for x, v in out.items()}


class PartTable:
    """Border vertices (in a fixed order) and one vector for each of their labellings."""

    def __init__(self, border: list[int], table: dict[int, np.ndarray]):
        self.border, self.table = border, table

    def bit(self, colour: int, vertex: int) -> int:
        return colour >> self.border.index(vertex) & 1


def joint_border(one: list[int], two: list[int], drop: set[int]) -> list[int]:
    return [v for v in [*one, *two] if v not in drop]


def project(colour: int, border: list[int], onto: list[int]) -> int:
    out = 0
    for i, v in enumerate(onto):
        if v in border and colour >> border.index(v) & 1:
            out |= 1 << i
    return out


def merge_tables(problem: VectorProblem, upper: PartTable, a: int, lower: PartTable, b: int, w: int, helper: bool, drop: set[int], most: int | None = None) -> PartTable:
    border = joint_border(upper.border, lower.border, drop)
    size = len(next(iter(upper.table.values()))) + len(next(iter(lower.table.values()))) - 1
    if most is not None:
        size = min(size, most + 1)
    out: dict[int, np.ndarray] = {}
    for p_colour, p in upper.table.items():
        for q_colour, q in lower.table.items():
            got = pair(problem, p, 0, p_colour, upper.bit(p_colour, a), q, 0, q_colour, lower.bit(q_colour, b), w, helper, most)
            if got is None:
                continue
            colour = project(p_colour, upper.border, border) | project(q_colour, lower.border, border)
            cell = out.setdefault(colour, np.full(size, INF, np.int64))
            start, v = got
            part = cell[start : start + len(v)]
            np.minimum(part, v[: len(part)], out=part)
    return PartTable(border, out)


def put_over(problem: VectorProblem, one: int, v: int, lower: PartTable, c: int, w: int, helper: bool, drop: bool, most: int | None = None) -> PartTable:
    """merge_tables() of a single vertex v, which counts for `one` vertices, with the table of its first child, by shifts instead of convolutions."""
    at = lower.border.index(c)
    below = (1 << at) - 1
    length = len(next(iter(lower.table.values()))) + one
    size = length if most is None else min(length, most + 1)
    out: dict[int, np.ndarray] = {}

    def reach(colour: int, shift: int, vec: np.ndarray, cost: int) -> None:
        cell = out.get(colour)
        if cell is None:
            cell = out[colour] = np.full(size, INF, np.int64)
        part = cell[shift : shift + len(vec)]
        vec = vec[: len(part)]
        np.minimum(part, vec + cost if cost else vec, out=part)

    span = problem.kind == "span"
    for q_colour, q in lower.table.items():
        y = q_colour >> at & 1
        # v comes first in the border
        rest = ((q_colour & below) | (q_colour >> at + 1 << at) if drop else q_colour) << 1
        for x in (0, 1):
            if helper and x != y:
                continue
            if not span:
                reach(rest | x, one * x, q, w if x != y and not helper else 0)
            elif x == y == 1:
                reach(rest | 1, one, q, 0 if helper else w)
            elif not x:
                reach(rest, 0, q, 0)
            elif q_colour == 0 and q[0] < INF:
                reach(1, one, q[:1], 0)
    for vec in out.values():
        np.minimum(vec, INF, out=vec)
        if problem.cap is not None:
            vec[vec > problem.cap] = INF
    return PartTable([v, *[b for b in lower.border if not (drop and b == c)]], out)


def fold_piece(problem: VectorProblem, node: list[int], parent: dict[int, int], aux: dict[int, bool], edge_w: dict[int, int], outer: dict[int, int], most: int | None = None, known: dict[int, PartTable] | None = None, sizes: dict[int, int] | None = None) -> PartTable:
    """The table of one piece. outer: number of cut edges at each vertex; parents outside the piece are absent. most: vectors go up to so many vertices labelled 1.

    known: tables of vertices whose children are not given. sizes: how many vertices each one counts for (None: 1).
    """
    sign = 1 if problem.sense == "min" else -1
    inside = set(node)
    size_of = (lambda v: 0 if aux[v] else 1) if sizes is None else (lambda v: 0 if aux[v] else sizes[v])
    kids: dict[int, list[int]] = {}
    root = None
    for v in node:
        if parent.get(v) in inside:
            kids.setdefault(parent[v], []).append(v)
        else:
            root = v
    order = [root]
    for v in order:
        order += kids.get(v, [])
    tables: dict[int, PartTable] = {}
    for v in reversed(order):
        mine = known.get(v) if known else None
        for c in kids.get(v, []):
            shut = not outer.get(c, 0)
            # the root of a whole tree keeps its label until the last child is in; it is dropped at the end
            if mine is None:
                mine = put_over(problem, size_of(v), v, tables.pop(c), c, sign * edge_w[c], aux[c], shut, most)
            else:
                mine = merge_tables(problem, mine, v, tables.pop(c), c, sign * edge_w[c], aux[c], {c} if shut else set(), most)
        tables[v] = mine or PartTable([v], _vertex(size_of(v), most))
    done = tables[root]
    keep = [v for v in done.border if outer.get(v, 0)]
    if keep != done.border:
        size = len(next(iter(done.table.values())))
        out: dict[int, np.ndarray] = {}
        for colour, vec in done.table.items():
            cell = out.setdefault(project(colour, done.border, keep), np.full(size, INF, np.int64))
            np.minimum(cell, vec, out=cell)
        # without a border, a labelling says nothing about which vertices are 1
        done = PartTable(keep, out)
    return done


def reached(par: np.ndarray, aux: np.ndarray, border: np.ndarray, most: int) -> list[int]:
    """Vertices from which a connected set of at most `most` counted vertices comes down to a border vertex (and at times a few more above)."""
    out: set[int] = set()
    for v in border.tolist():
        count = 0 if aux[v] else 1
        out.add(v)
        while (up := int(par[v])) >= 0:
            count += not aux[up]
            # a helper shares the label of the vertex above it, so the walk does not end at one
            if count > most and not aux[v]:
                break
            out.add(up)
            v = up
    return sorted(out)


def span_pieces(problem: VectorProblem, code: np.ndarray, node: np.ndarray, above: np.ndarray, aux: np.ndarray, edge_w: np.ndarray, border: np.ndarray, most: int) -> list[PartTable] | None:
    """fold_piece() of many pieces for spans of at most `most` vertices, degree by degree on arrays.

    Rows are sorted by (piece, vertex); border holds the places of the ends of cut edges. The best
    set of d vertices with a given top follows from those of fewer vertices at its children, so all
    vertices go at once. Only near a border do labellings matter; that part is folded vertex by
    vertex. None: too many numbers at once.
    """
    n, sign = len(node), 1 if problem.sense == "min" else -1
    par = positions(code, node, above)
    begins = np.flatnonzero(np.r_[True, code[1:] != code[:-1]])
    counted = np.add.reduceat((~aux).astype(np.int64), begins)
    k = int(min(most, counted.max()))
    kid, second = np.full(n, n), np.full(n, n)
    below = np.flatnonzero(par >= 0)
    below = below[np.argsort(par[below], kind="stable")]
    first = np.r_[True, par[below[1:]] != par[below[:-1]]] if len(below) else np.zeros(0, bool)
    kid[par[below[first]]], second[par[below[~first]]] = below[first], below[~first]
    two = np.flatnonzero((second < n) & ~aux)
    forked = bool((second < n).any())
    if forked and (n + 1) * (k + 1) > SPAN_NUMBERS:
        return None
    near = reached(par, aux, border, most)
    inside = np.zeros(n + 1, bool)
    inside[near] = True
    hung = np.unique(np.r_[kid[near], second[near]]) if near else np.zeros(0, np.int64)
    hung = hung[(hung < n) & ~inside[hung]]
    # helpers, the lowest first: they have a number of the same degree as their children
    levels: list[np.ndarray] = []
    waiting = np.flatnonzero(aux)
    open_ = np.r_[aux, False]
    while len(waiting):
        now = waiting[~open_[kid[waiting]] & ~open_[second[waiting]]]
        open_[now] = False
        levels.append(now)
        waiting = waiting[open_[waiting]]
    no_top = np.r_[np.array(near, np.int64), np.flatnonzero(aux)]
    w = sign * edge_w
    best = np.full((len(begins), k + 1), INF, np.int64)
    best[:, 0] = 0
    held = np.full((len(hung), k + 1), INF, np.int64)
    held[aux[hung], 0] = 0
    #: by degree: what a vertex gives its parent, nothing taken being 0; the last place stands for no child
    gives = [np.zeros(n + 1, np.int64)]
    for d in range(1, k + 1):
        top = gives[-1][kid]
        if len(two):
            a, b = kid[two], second[two]
            least = top[two]
            for i in range(d - 1):
                np.minimum(least, gives[i][a] + gives[d - 1 - i][b], out=least)
            top[two] = np.minimum(least, INF)
        now = np.empty(n + 1, np.int64)
        np.add(top, w, out=now[:n])
        np.minimum(now, INF, out=now)
        now[n] = INF
        gives.append(now)
        for level in levels:
            least = now[kid[level]]
            if forked:
                for i in range(d):
                    np.minimum(least, gives[i][kid[level]] + gives[d - i][second[level]], out=least)
            now[level] = np.minimum(least, INF)
        held[:, d] = np.where(aux[hung], now[hung], top[hung])
        top[no_top] = INF
        best[:, d] = np.minimum.reduceat(top, begins)
        if not forked:
            gives = [now]
    best[best > INF // 2] = held[held > INF // 2] = INF
    out = [PartTable([], {0: best[p, : min(most, int(counted[p])) + 1]}) for p in range(len(begins))]
    if not near:
        return out
    piece = np.searchsorted(begins, border, "right") - 1
    for p, v in zip(piece.tolist(), border.tolist()):
        out[p].border.append(v)
    tables = {c: PartTable([c], {0: np.r_[0, np.full(k, INF)], 1: row}) for c, row in zip(hung.tolist(), held)}
    ends = dict.fromkeys(border.tolist(), 1)
    for top_ in near:
        if par[top_] >= 0 and inside[par[top_]]:
            continue
        own = [top_]
        for v in own:
            if inside[v]:
                own += [int(c) for c in (kid[v], second[v]) if c < n]
        got = fold_piece(problem, own, {v: int(par[v]) for v in own[1:]}, {v: bool(aux[v]) for v in own}, {v: int(edge_w[v]) for v in own}, ends, most, {v: tables[v] for v in own if not inside[v]})
        mine = out[int(np.searchsorted(begins, top_, "right")) - 1]
        size = len(mine.table[0])
        for colour, vec in got.table.items():
            cell = mine.table.setdefault(project(colour, got.border, mine.border), np.full(size, INF, np.int64))
            part = cell[: len(vec)]
            np.minimum(part, vec[: len(part)], out=part)
    return [PartTable(node[t.border].tolist(), t.table) for t in out]


@dataclass
class _Pieces:
    """Sorted rows of pieces as arrays of their own vertices; ends: the upper ends of the edges to the pieces below, hanging: these pieces' roots."""

    tree: np.ndarray
    comp: np.ndarray
    node: np.ndarray
    above: np.ndarray
    aux: np.ndarray
    edge_w: np.ndarray
    begins: np.ndarray
    code: np.ndarray
    ends: np.ndarray
    hanging: np.ndarray


def _pieces(table: pa.Table) -> _Pieces:
    own = table.filter(pc.is_null(table["leaf"]))
    tree, comp, node = (own[c].to_numpy() for c in ("tree_id", "comp_id", "node_id"))
    order = np.lexsort((node, comp, tree))
    tree, comp, node = tree[order], comp[order], node[order]
    new = np.r_[True, (tree[1:] != tree[:-1]) | (comp[1:] != comp[:-1])]
    begins = np.flatnonzero(new)
    place = {(t, c): i for i, (t, c) in enumerate(zip(tree[begins].tolist(), comp[begins].tolist()))}
    cut = table.filter(pc.is_valid(table["leaf"])).select(["tree_id", "comp_id", "parent_id", "leaf"]).to_pydict()
    bounds, ends = [*begins.tolist(), len(node)], []
    for t, c, v in zip(cut["tree_id"], cut["comp_id"], cut["parent_id"]):
        a, b = bounds[place[t, c] : place[t, c] + 2]
        ends.append(a + int(np.searchsorted(node[a:b], v)))
    aux = np.asarray(own["is_aux"].to_numpy(zero_copy_only=False), bool)[order]
    above, edge_w = (own[c].fill_null(f).to_numpy()[order] for c, f in (("parent_id", -1), ("edge_w", 0)))
    return _Pieces(tree, comp, node, above, aux, edge_w, begins, np.cumsum(new) - 1, np.array(ends, np.int64), np.array(cut["leaf"], np.int64))


def _span_run(problem: VectorProblem, table: pa.Table, most: int) -> tuple[list[int], list[int], list[PartTable] | None]:
    """span_pieces() of sorted rows of pieces: trees, pieces and tables."""
    p = _pieces(table)
    border = np.unique(np.r_[np.flatnonzero((p.node == p.comp) & (p.above >= 0)), p.ends])
    made = span_pieces(problem, p.code, p.node, p.above, p.aux, p.edge_w, border, most)
    return p.tree[p.begins].tolist(), p.comp[p.begins].tolist(), made


def _blocks(trees, parts, tables: list[PartTable], length: int) -> pa.RecordBatch:
    rows: list[list] = [[], [], [], [], [], []]
    for tree, part, t in zip(trees, parts, tables):
        for colour, vec in t.table.items():
            for start in range(0, len(vec), length):
                for column, value in zip(rows, (tree, part, t.border, colour, start, vec[start : start + length])):
                    column.append(value)
    types = [pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.int32(), pa.int64(), pa.list_(pa.int64())]
    return pa.RecordBatch.from_arrays([pa.array(r, t) for r, t in zip(rows, types)], ["tree_id", "part_id", "border", "colour", "start", "vals"])


def local_vectors(ready: Prepared, problem: VectorProblem, block: int, most: int | None = None, sized: bool = False) -> DataFrame:
    """VECBLK of every piece, each computed in one task. sized: a vertex counts for as many vertices as its weight says."""
    prepare(ready.bt.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spans = problem.kind == "span" and most is not None
        for table in _sorted_runs(batches, ["tree_id", "comp_id"], SPAN_ROWS if spans else 20_000):
            if spans:
                at, pieces, made = _span_run(problem, table, most)
                if made is not None:
                    yield _blocks(at, pieces, made, block)
                    continue
            trees_, comps = table["tree_id"].to_numpy(), table["comp_id"].to_numpy()
            starts = np.flatnonzero(np.r_[True, (trees_[1:] != trees_[:-1]) | (comps[1:] != comps[:-1])]).tolist()
            made = []
            for a, b in zip(starts, [*starts[1:], len(comps)]):
                rows, comp = table.slice(a, b - a), int(comps[a])
                outer: dict[int, int] = {}
                for end in rows.filter(pc.is_valid(rows["leaf"]))["parent_id"].to_pylist():
                    outer[end] = outer.get(end, 0) + 1
                own = rows.filter(pc.is_null(rows["leaf"]))
                node = own["node_id"].to_pylist()
                parent = dict(zip(node, own["parent_id"].to_pylist()))
                if parent.get(comp) is not None:
                    outer[comp] = outer.get(comp, 0) + 1
                sizes = dict(zip(node, own["node_w"].to_pylist())) if sized else None
                made.append(fold_piece(problem, node, parent, dict(zip(node, own["is_aux"].to_pylist())), dict(zip(node, own["edge_w"].fill_null(0).to_pylist())), outer, most, sizes=sizes))
            yield _blocks(trees_[starts].tolist(), comps[starts].tolist(), made, block)

    rows = piece_rows(ready.bt, ready.dec).select("tree_id", "comp_id", "node_id", "parent_id", "is_aux", "node_w", "edge_w", "leaf")
    return rows.repartition("tree_id", "comp_id").sortWithinPartitions("tree_id", "comp_id").mapInArrow(run, VECBLK)


def merge_edges(ready: Prepared) -> DataFrame:
    """What a merge needs of each piece edge: its two end vertices, weight, whether it hangs a helper."""
    lower = ready.bt.select("tree_id", F.col("node_id").alias("comp_id"), "is_aux", "edge_w")
    comp = ready.dec.comp.where("parent_comp IS NOT NULL")
    return (F.broadcast(comp) if ready.dec.few else comp).join(lower, ["tree_id", "comp_id"]).select("tree_id", F.col("comp_id").alias("child_comp"), F.col("attach_node").alias("upper_end"), F.col("comp_id").alias("lower_end"), F.col("is_aux").alias("helper"), F.coalesce("edge_w", F.lit(0)).alias("w"))


def _open_ends(schedule: DataFrame, edges: DataFrame) -> DataFrame:
    """For each merge, whether its two end vertices have no cut edge left after it.

    Vertices may end several cut edges; an end is closed by the last merge that uses it.
    """

    merges = schedule.join(edges, ["tree_id", "child_comp"])
    uses = merges.select("tree_id", "child_comp", "step", "half", F.explode(F.array("upper_end", "lower_end")).alias("vertex"))
    last = Window.partitionBy("tree_id", "vertex").orderBy(F.col("step").desc(), F.col("half").desc(), F.col("child_comp").desc())
    closing = uses.withColumn("n", F.row_number().over(last)).where("n = 1").groupBy("tree_id", "child_comp").agg(F.collect_set("vertex").alias("closed"))
    return merges.join(closing, ["tree_id", "child_comp"], "left").withColumn("closed", F.coalesce("closed", F.expr("cast(array() as array<bigint>)")))


def _lists(column: pa.Array) -> tuple[np.ndarray, list[int]]:
    """All values of a list column, and where each list begins and ends, without a Python object for each value."""
    return column.values.to_numpy(zero_copy_only=False), column.offsets.to_pylist()


def _pairs(problem: VectorProblem, most: int | None = None):
    sign = 1 if problem.sense == "min" else -1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            small = [n for n in batch.schema.names if n not in ("p_vals", "q_vals")]
            p_all, p_at = _lists(batch.column("p_vals"))
            q_all, q_at = _lists(batch.column("q_vals"))
            keep: list[list] = [[], [], [], [], []]
            vectors = []
            for i, r in enumerate(batch.select(small).to_pylist()):
                x = r["p_colour"] >> r["p_border"].index(r["upper_end"]) & 1
                y = r["q_colour"] >> r["q_border"].index(r["lower_end"]) & 1
                got = pair(problem, p_all[p_at[i] : p_at[i + 1]], r["p_start"], r["p_colour"], x, q_all[q_at[i] : q_at[i + 1]], r["q_start"], r["q_colour"], y, sign * r["w"], r["helper"], most)
                if got is None:
                    continue
                border = joint_border(r["p_border"], r["q_border"], set(r["closed"]))
                colour = project(r["p_colour"], r["p_border"], border) | project(r["q_colour"], r["q_border"], border)
                for column, value in zip(keep, (r["tree_id"], r["out_part"], border, colour, got[0])):
                    column.append(value)
                vectors.append(got[1])
            types = [pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.int32(), pa.int64()]
            edges = np.cumsum([0, *map(len, vectors)]).astype(np.int32)
            vals = pa.ListArray.from_arrays(pa.array(edges), pa.array(np.concatenate(vectors) if vectors else np.zeros(0, np.int64)))
            yield pa.RecordBatch.from_arrays([*[pa.array(c, t) for c, t in zip(keep, types)], vals], ["tree_id", "part_id", "border", "colour", "start", "vals"])

    return run


def pair_round(blocks: DataFrame, merges: DataFrame, problem: VectorProblem, most: int | None = None, pairs=None, tasks: int | None = None) -> DataFrame:
    """First round of a merge turn: one row of work for each pair of blocks, spread over all tasks.

    pairs: what is done with the rows of work (None: dense vectors). tasks: how many, where rows are short but dear.
    """
    left = blocks.select("tree_id", F.col("part_id").alias("left_part"), F.col("border").alias("p_border"), F.col("colour").alias("p_colour"), F.col("start").alias("p_start"), F.col("vals").alias("p_vals"))
    right = blocks.select("tree_id", F.col("part_id").alias("right_part"), F.col("border").alias("q_border"), F.col("colour").alias("q_colour"), F.col("start").alias("q_start"), F.col("vals").alias("q_vals"))
    # the plan has about 14 m rows in all; Spark broadcasts it where it is small
    work = merges.select("tree_id", "left_part", "right_part", "out_part", "upper_end", "lower_end", "helper", "w", "closed").join(left, ["tree_id", "left_part"]).join(right, ["tree_id", "right_part"])
    dealt = work.repartition(*[tasks] * (tasks is not None), "tree_id", "out_part", "p_start", "q_start")
    return dealt.mapInArrow(pairs or _pairs(problem, most), VECBLK)


def unify_round(pairs: DataFrame, block: int) -> DataFrame:
    """Second round: every element goes to the owner of (part, labelling, index) and the least one stays; then blocks again."""
    elements = pairs.select("tree_id", "part_id", "border", "colour", "start", F.posexplode("vals").alias("at", "val")).withColumn("idx", F.col("start") + F.col("at"))
    least = elements.where(F.col("val") < INF).groupBy("tree_id", "part_id", "border", "colour", "idx").agg(F.min("val").alias("val"))
    blocks = least.groupBy("tree_id", "part_id", "border", "colour", F.floor(F.col("idx") / block).alias("no")).agg(F.array_sort(F.collect_list(F.struct("idx", "val"))).alias("items"))
    # indexes that no pair reached are impossible: they are sorted in
    first, last = F.col("items")[0]["idx"], F.element_at("items", -1)["idx"]
    missing = F.array_except(F.sequence(first, last), F.transform("items", lambda x: x["idx"]))
    filled = F.array_sort(F.concat("items", F.transform(missing, lambda i: F.struct(i.alias("idx"), F.lit(INF).alias("val")))))
    dense = F.transform(F.when(F.size("items") == last - first + 1, F.col("items")).otherwise(filled), lambda x: x["val"])
    return blocks.select("tree_id", "part_id", "border", "colour", first.alias("start"), dense.alias("vals"))


def _merge_alone(problem: VectorProblem, block: int, most: int | None = None):
    """Whole merges of a tree (or of one out part) in one task, in order."""
    sign = 1 if problem.sense == "min" else -1

    def run(table: pa.Table) -> pa.Table:
        parts: dict[int, PartTable] = {}
        sizes: dict[int, int] = {}
        merges = []
        rows = table.to_pylist()
        for r in rows:
            if r["vals"] is None:
                merges.append(r)
            else:
                sizes[r["part_id"]] = max(sizes.get(r["part_id"], 0), r["start"] + len(r["vals"]))
        for r in rows:
            if r["vals"] is not None:
                t = parts.setdefault(r["part_id"], PartTable(list(r["border"]), {}))
                vec = t.table.setdefault(r["colour"], np.full(sizes[r["part_id"]], INF, np.int64))
                vec[r["start"] : r["start"] + len(r["vals"])] = r["vals"]
        for r in sorted(merges, key=lambda r: (r["step"], r["half"], r["child_comp"])):
            low = parts.pop(r["right_part"])
            parts[r["out_part"]] = merge_tables(problem, parts.pop(r["left_part"]), r["upper_end"], low, r["lower_end"], sign * r["w"], r["helper"], set(r["closed"]), most)
        tree = rows[0]["tree_id"]
        return pa.Table.from_batches([_blocks([tree] * len(parts), list(parts), list(parts.values()), block)])

    return run


def _alone(blocks: DataFrame, merges: DataFrame, problem: VectorProblem, block: int, by: list[str], most: int | None = None) -> DataFrame:
    columns = ["tree_id", "part_id", "border", "colour", "start", "vals", "step", "half", "child_comp", "left_part", "right_part", "out_part", "upper_end", "lower_end", "helper", "w", "closed"]
    data = blocks.select("*", *[F.lit(None).alias(c) for c in columns if c not in blocks.columns]).select(*columns, *[c for c in by if c not in columns])
    work = merges.select("*", *[F.lit(None).alias(c) for c in columns if c not in merges.columns]).select(*columns, *[c for c in by if c not in columns])
    types = dict(merges.dtypes) | dict(blocks.dtypes)
    cast = lambda df: df.select(*[F.col(c).cast(types[c]).alias(c) for c in [*columns, *[c for c in by if c not in columns]]])
    return cast(data).unionAll(cast(work)).groupBy(*by).applyInArrow(_merge_alone(problem, block, most), VECBLK)


def _levels_schedule(comp: DataFrame) -> DataFrame:
    """Bottom-up merging of the tree of pieces: as many turns as it is deep."""
    from .baselines import depths

    with_depth, deepest = depths(comp.select("tree_id", F.col("comp_id").alias("node_id"), F.col("parent_comp").alias("parent_id")))
    rows = comp.where("parent_comp IS NOT NULL").join(with_depth.withColumnRenamed("node_id", "comp_id"), ["tree_id", "comp_id"])
    second = F.row_number().over(Window.partitionBy("tree_id", "parent_comp").orderBy("comp_id")).cast("int")
    return rows.select("tree_id", (F.lit(deepest + 1) - F.col("depth")).cast("int").alias("step"), second.alias("half"), F.col("comp_id").alias("child_comp"), F.col("parent_comp").alias("left_part"), F.col("comp_id").alias("right_part"), F.col("parent_comp").alias("out_part"))


FINISHES = ("grid", "pairs", "levels", "master")


def solve_vectors(tree: DataFrame | Prepared, problem: VectorProblem, m: int = 8, seed: int = 0, finish: str = "grid", block: int | None = None, local_elements: int | None = None, rules: Rules = Rules(), shape: str = "balanced", most: int | None = None, sized: bool = False) -> DataFrame:
    """(tree_id, idx, value) for every number of original vertices labelled 1 (up to most, where given); infeasible numbers are left out.

    finish 'grid': scheduled merges on a grid of blocks; merging goes to one task for each
    tree once all vectors together have at most local_elements elements (None: what one
    machine may hold, n^(4/3)/m, LOCAL_FLOOR at least; 0: never).
    'pairs': scheduled, each merge whole in one task. 'levels': bottom-up order. 'master':
    all vectors of a tree in one task at once. The last three are baselines.
    """
    if finish not in FINISHES:
        raise ValueError(f"finish must be one of {FINISHES}")
    ready = tree if isinstance(tree, Prepared) else prepare_tree(tree, m, seed, shape, rules=rules)
    length = block or max(256, -(-ready.dec.n // max(1, int(ready.dec.m**0.5))))
    if local_elements is None:
        local_elements = max(LOCAL_FLOOR, int(ready.dec.n ** (4 / 3) / max(1, ready.dec.m)))
    blocks = materialise(local_vectors(ready, problem, length, most, sized), "vectors")
    schedule = _levels_schedule(ready.dec.comp) if finish == "levels" else plan.build(ready.dec.comp)
    merges = materialise(_open_ends(schedule, merge_edges(ready)), "merges")
    turns = plan.steps_of(merges)
    if finish == "master":
        blocks = _alone(blocks, merges, problem, length, ["tree_id"], most)
    else:
        for i, (step, half) in enumerate(turns):
            if finish == "grid" and local_elements and blocks.agg(F.sum(F.size("vals"))).first()[0] <= local_elements:
                rest = merges.where((F.col("step") > step) | ((F.col("step") == step) & (F.col("half") >= half)))
                blocks = _alone(blocks, rest, problem, length, ["tree_id"], most)
                break
            now = merges.where((F.col("step") == step) & (F.col("half") == half))
            used = now.select("tree_id", F.explode(F.array("left_part", "right_part")).alias("part_id"), "out_part")
            idle = blocks.join(used.select("tree_id", "part_id"), ["tree_id", "part_id"], "left_anti").select(*blocks.columns)
            if finish == "grid":
                merged = unify_round(pair_round(blocks, now, problem, most), length)
            else:
                busy = blocks.join(used, ["tree_id", "part_id"])
                merged = _alone(busy, now, problem, length, ["tree_id", "out_part"], most)
            blocks = materialise(idle.unionByName(merged), "vectors")
    sign = 1 if problem.sense == "min" else -1
    flat = blocks.select("tree_id", "start", F.posexplode("vals").alias("at", "v"))
    return flat.groupBy("tree_id", (F.col("start") + F.col("at")).alias("idx")).agg(F.min("v").alias("v")).where(F.col("v") < INF // 2).select("tree_id", "idx", (F.col("v") * sign).alias("value"))


def answer_at(profile: DataFrame, tree: DataFrame, problem: VectorProblem, k: int | None = None) -> DataFrame:
    """ANSWER at k, or at half of the vertices (rounded down)."""
    sizes = tree.groupBy("tree_id").agg(F.count(F.lit(1)).alias("n"))
    wanted = sizes.select("tree_id", (F.floor(F.col("n") / 2) if k is None else F.lit(k)).cast("long").alias("idx"))
    return wanted.join(profile, ["tree_id", "idx"], "left").select("tree_id", F.lit(problem.name).alias("problem"), F.col("idx").alias("param"), "value", F.col("value").isNotNull().alias("feasible"))


def over_light_edges(ready: Prepared, light: list[int]) -> DataFrame:
    """(top, up, size): what is left of a tree whose edges are contracted, but those above the given vertices and above pieces.

    size counts the original vertices of a top's part; the row of a piece's root with its upper end has size 0.
    """
    prepare(ready.bt.sparkSession)
    kept = np.array(sorted(light), np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _sorted_runs(batches, ["tree_id", "comp_id"]):
            p = _pieces(table)
            par = positions(p.code, p.node, p.above)
            tops = (par < 0) | np.isin(p.node, kept)
            ptr = np.where(tops, np.arange(len(par)), par)
            while not np.array_equal(far := ptr[ptr], ptr):
                ptr = far
            sizes = np.bincount(ptr, ~p.aux, len(par)).astype(np.int64)
            at = np.flatnonzero(tops)
            top, size = np.r_[p.node[at], p.hanging], np.r_[sizes[at], np.zeros(len(p.ends), np.int64)]
            up = np.r_[np.where(par[at] >= 0, p.node[ptr[par[at]]], -1), p.node[ptr[p.ends]]]
            yield pa.RecordBatch.from_arrays([pa.array(top), pa.array(up, mask=up < 0), pa.array(size)], ["top", "up", "size"])

    rows = piece_rows(ready.bt, ready.dec).select("tree_id", "comp_id", "node_id", "parent_id", "is_aux", "edge_w", "leaf")
    return rows.repartition("tree_id", "comp_id").sortWithinPartitions("tree_id", "comp_id").mapInArrow(run, "top long, up long, size long")


def _light_bisection(tree: DataFrame, ready: Prepared, n: int, m: int, options: dict) -> DataFrame | None:
    """ANSWER of one large tree from its lightest edges, or None where these do not prove it.

    Over L edges the tree is a few parts with sizes. A bisection that cuts another edge costs at least the
    least weight among the others, so one of that cost or less that cuts only the L is a best one.
    """
    edges = ready.bt.where("NOT is_aux AND parent_id IS NOT NULL").select(F.coalesce("edge_w", F.lit(0)).alias("w"), "node_id")
    lightest = edges.orderBy("w", "node_id").limit(LIGHT_EDGES[-1] + 1).collect()
    if len(lightest) <= LIGHT_EDGES[-1] or lightest[0]["w"] < 0:
        return None
    sizes: dict[int, int] = {}
    up: dict[int, int] = {}
    for r in over_light_edges(ready, [r["node_id"] for r in lightest[:-1]]).collect():
        sizes[r["top"]] = sizes.get(r["top"], 0) + r["size"]
        if r["up"] is not None:
            up[r["top"]] = r["up"]
    (tree_id,) = tree.select("tree_id").first()
    for light in LIGHT_EDGES:
        weight = {r["node_id"]: r["w"] for r in lightest[:light]}
        into: dict[int, int] = {}
        for v in sizes:
            way = []
            while v not in into and v in up and v not in weight:
                way.append(v)
                v = up[v]
            into |= dict.fromkeys([*way, v], into.get(v, v))
        size: dict[int, int] = {}
        for v, s in sizes.items():
            size[into[v]] = size.get(into[v], 0) + s
        if max(size.values()) > n - n // 2:
            continue
        rows = [(tree_id, v >> 2, into[up[v]] >> 2 if v in up else None, 0, s, weight.get(v)) for v, s in size.items()]
        small = tree.sparkSession.createDataFrame(rows, TREE)
        wide = {"block": max(256, -(-n // max(1, int(m**0.5)))), "local_elements": max(LOCAL_FLOOR, int(n ** (4 / 3) / max(1, m)))}
        profile = solve_vectors(small, replace(BISECTION, cap=lightest[light]["w"]), m, most=n // 2, sized=True, **(wide | {k: v for k, v in options.items() if v is not None}))
        out = materialise(answer_at(profile, tree, BISECTION), "answer")
        if out.first()["feasible"]:
            return out
    return None


def ranked_edges(ready: Prepared) -> list[tuple[int, int, int]]:
    """(lower end, weight, size of its subtree) of the RANKED_EDGES edges with the largest size to weight, no weight coming first."""
    prepare(ready.bt.sparkSession)
    comp = ready.dec.comp.select("comp_id", "parent_comp", "n_vertices").collect()
    below = {r["comp_id"]: r["n_vertices"] for r in comp}
    if ready.bt.where("is_aux").limit(1).count():
        below = {r["top"]: r["size"] for r in over_light_edges(ready, []).where("size > 0 OR up IS NULL").collect()}
        below |= {r["comp_id"]: 0 for r in comp if r["comp_id"] not in below}
    kids: dict[int | None, list[int]] = {}
    for r in comp:
        kids.setdefault(r["parent_comp"], []).append(r["comp_id"])
    order = list(kids[None])
    for v in order:
        order += kids.get(v, [])
    for v in reversed(order):
        below[v] += sum(below[c] for c in kids.get(v, []))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _sorted_runs(batches, ["tree_id", "comp_id"]):
            p = _pieces(table)
            par = positions(p.code, p.node, p.above)
            size = (~p.aux).astype(np.int64)
            np.add.at(size, p.ends, np.array([below[v] for v in p.hanging.tolist()], np.int64))
            depth, ptr = (par >= 0).astype(np.int64), np.where(par >= 0, par, np.arange(len(par)))
            while not np.array_equal(far := ptr[ptr], ptr):
                depth, ptr = depth + depth[ptr], far
            sums, ups = size.tolist(), par.tolist()
            for v in np.argsort(-depth, kind="stable").tolist():
                if ups[v] >= 0:
                    sums[ups[v]] += sums[v]
            size = np.array(sums, np.int64)
            at = np.flatnonzero((p.above >= 0) & ~p.aux & (size >= p.edge_w))
            yield pa.RecordBatch.from_arrays([pa.array(x[at]) for x in (p.node, p.edge_w, size)], ["node_id", "w", "size"])

    rows = piece_rows(ready.bt, ready.dec).select("tree_id", "comp_id", "node_id", "parent_id", "is_aux", "edge_w", "leaf")
    edges = rows.repartition("tree_id", "comp_id").sortWithinPartitions("tree_id", "comp_id").mapInArrow(run, "node_id long, w long, size long")
    ratio = F.when(F.col("w") <= 0, F.lit(float("inf"))).otherwise(F.col("size") / F.col("w"))
    return [tuple(r) for r in edges.orderBy(ratio.desc(), "w", "node_id").limit(RANKED_EDGES).collect()]


def _cut_tree(sizes: dict[int, int], up: dict[int, int], cut: set[int]) -> tuple[dict[int, int], dict[int, int]]:
    """(size, up) of the parts that are left when only the given edges are not contracted."""
    into: dict[int, int] = {}
    for v in sizes:
        way = []
        while v not in into and v in up and v not in cut:
            way.append(v)
            v = up[v]
        into |= dict.fromkeys([*way, v], into.get(v, v))
    size: dict[int, int] = {}
    for v, s in sizes.items():
        size[into[v]] = size.get(into[v], 0) + s
    return size, {v: into[up[v]] for v in size if v in up}


def _binary(up: dict[int, int], size: dict[int, int]) -> tuple[list[int], np.ndarray]:
    """(vertices, places of their parents) of a small tree with helpers, which come last, so that none has more than two children."""
    node = sorted(size)
    place = {v: i for i, v in enumerate(node)}
    par = [place[up[v]] if v in up else -1 for v in node]
    kids: dict[int, list[int]] = {}
    for i, p in enumerate(par):
        kids.setdefault(p, []).append(i)
    kids.pop(-1)
    for v, level in kids.items():
        while len(level) > 2:
            for i in range(0, len(level) - 1, 2):
                par[level[i]] = par[level[i + 1]] = len(par)
                par.append(v)
                level[i] = len(par) - 1
            level = level[::2]
    return node, np.array(par, np.int64)


def _runs_plan(par: np.ndarray, m: int, parts: int, seed: int = 0) -> tuple[np.ndarray, list[tuple[int, int, int, int, int, list[int]]]]:
    """About `parts` pieces of a small binary tree (the top of each vertex's) and their merges in order, each with the ends that it closes.

    A merge is (step, half, child piece, upper end, out part, closed).
    """
    k = len(par)
    top, *_ = contract_arrays(np.zeros(k, np.int64), np.arange(k), par, np.ones(k, np.int64), max(1.0, k / max(1, m)), parts, seed)
    parents = {v: int(top[par[v]]) if par[v] >= 0 else None for v in np.unique(top).tolist()}
    merges = sorted((step, half, child, int(par[child]), left) for step, half, child, left, _, _ in plan.build_plan(parents))
    last = {v: i for i, (_, _, child, above, _) in enumerate(merges) for v in (child, above)}
    return top, [(*x, sorted(v for v in {x[2], x[3]} if last[v] == i)) for i, x in enumerate(merges)]


def solve_runs(spark: SparkSession, tree_id: int, up: dict[int, int], size: dict[int, int], weight: dict[int, int], m: int, n: int, most: int, cap: int, parts: int | None = None) -> runs.Runs:
    """Profile up to `most` of the cuts of a small tree, each vertex counting for its size: pieces are folded in a task each, and merged as scheduled on a grid of blocks of runs.

    parts: about so many pieces (None: two for each core).
    """
    prepare(spark)
    node, par = _binary(up, size)
    cores = spark.sparkContext.defaultParallelism
    top, merges = _runs_plan(par, cores, 2 * cores if parts is None else parts)
    ends = {v for _, _, child, above, _, _ in merges for v in (child, above)}
    length = max(256, -(-n // max(1, int(m**0.5))))
    rows = []
    for piece in np.unique(top).tolist():
        own = np.flatnonzero(top == piece).tolist()
        real = [node[v] if v < len(node) else None for v in own]
        rows.append((tree_id, piece, own, par[own].tolist(), [v is None for v in real], [size.get(v, 0) for v in real], [weight.get(v, 0) for v in real], [v for v in own if v in ends]))
    schema = "tree_id long, part_id long, node array<long>, up array<long>, aux array<boolean>, size array<long>, weight array<long>, ends array<long>"
    pieces = spark.createDataFrame(spark.sparkContext.parallelize(rows, len(rows)), schema)
    blocks = materialise(pieces.mapInArrow(runs.pieces_of_runs(most, cap, length), VECBLK), "vectors")
    schema = "tree_id long, left_part long, right_part long, out_part long, upper_end long, lower_end long, helper boolean, w long, closed array<long>"
    for turn in sorted({x[:2] for x in merges}):
        work = [(tree_id, left, child, left, above, child, child >= len(node), weight.get(node[child], 0) if child < len(node) else 0, closed) for *at, child, above, left, closed in merges if tuple(at) == turn]
        used = [v for r in work for v in r[1:3]]
        paired = pair_round(blocks, F.broadcast(spark.createDataFrame(work, schema)), BISECTION, most, runs.pairs_of_runs(most, cap, length), cores)
        merged = runs.unify_runs(paired, length, VECBLK)
        blocks = materialise(blocks.where(~F.col("part_id").isin(used)).unionByName(merged), "vectors")
    return runs.joined(r["vals"] for r in blocks.select("vals").collect())


def _ranked_parts(ready: Prepared) -> tuple[list[tuple[int, int, int]], dict[int, int], dict[int, int]]:
    """ranked_edges(), and what is left of the tree whose other edges are contracted (but those above pieces): sizes and parents."""
    edges = ranked_edges(ready)
    sizes: dict[int, int] = {}
    up: dict[int, int] = {}
    for r in over_light_edges(ready, [v for v, _, _ in edges]).collect():
        sizes[r["top"]] = sizes.get(r["top"], 0) + r["size"]
        if r["up"] is not None:
            up[r["top"]] = r["up"]
    return edges, sizes, up


def _raked_parts(tree: DataFrame, n: int, m: int) -> tuple[list[tuple[int, int, int]], dict[int, int], dict[int, int]] | None:
    """_ranked_parts() of one tree whose leaves are taken off in turns, without a decomposition. None: its paths are too long for that."""
    if (raked := rake(tree, n, max(m, -(-n // MOST_SHARE)))) is None:
        return None
    rows = largest(raked, RANKED_EDGES)
    up = closest(raked, {v: p for v, _, _, p in rows})
    release(*raked.turns, raked.rest)
    (root,) = tree.where("parent_id IS NULL").select("node_id").first()
    sizes = {root: n} | {v: s for v, _, s, _ in rows}
    for v, _, s, _ in rows:
        sizes[up[v]] -= s
    return [(v << 2, w, s) for v, w, s, _ in rows], {v << 2: s for v, s in sizes.items()}, {v << 2: p << 2 for v, p in up.items()}


def _ranked_bisection(tree: DataFrame, parts: tuple[list[tuple[int, int, int]], dict[int, int], dict[int, int]], n: int, m: int) -> DataFrame | None:
    """ANSWER of one large tree from the edges that move many vertices for their weight, or None where these do not prove it.

    Let the others have a weight of 1 at least and move at most r vertices for each unit. A best cut of cost c with others
    of weight o > 0 leaves, without these, a cut over the chosen edges that costs c - o and is at most r * o vertices off
    the half. So if no cut over the chosen edges that is d vertices off costs less than V - max(1, d / r), none costs less than V.
    """
    edges, sizes, up = parts
    free = sum(w == 0 for _, w, _ in edges)
    if not edges or min(w for _, w, _ in edges) < 0 or free > CUT_EDGES:
        return None
    weight = {v: w for v, w, _ in edges}
    half, best, first = n // 2, None, FIRST_EDGES
    while best is None and first <= 4 * FIRST_EDGES:
        size, above = _cut_tree(sizes, up, {v for v, _, _ in edges[: free + first]})
        for cap in FIRST_CAPS:
            got = runs.fold(above, size, weight, half, cap, FIRST_SUMS)
            if got is None or (best := runs.at(got, half)) is not None:
                break
        if got is None:
            break
        first *= 2
    if best is None:
        return None
    # heavier edges are in no better cut
    usable = [e for e in edges if e[1] <= best]
    r = max(1.0, *[s / w * (1 + 1e-9) for _, w, s in [*usable[CUT_EDGES:], edges[-1]] if w])
    cut = [v for v, _, _ in usable[:CUT_EDGES]]
    size, above = _cut_tree(sizes, up, set(cut))
    (tree_id,) = tree.select("tree_id").first()
    lo, hi, cost = got = solve_runs(tree.sparkSession, tree_id, above, size, weight, m, n, half + int(r * best) + 1, best)
    value = runs.at(got, half)
    off = np.maximum(np.maximum(lo - half, half - hi), 0)
    if value is None or (cost + np.maximum(1, np.ceil(off / r)) < value).any():
        return None
    row = (tree_id, BISECTION.name, half, value, True)
    return tree.sparkSession.createDataFrame([row], "tree_id long, problem string, param long, value long, feasible boolean")


def bisection(tree: DataFrame, m: int = 8, **options) -> DataFrame:
    """ANSWER at half of the vertices. A single large tree is first tried over a few of its edges, and else computed whole."""
    inner = F.approx_count_distinct("parent_id")
    n, trees, forking = tree.agg(F.count(F.lit(1)), F.count_if(F.col("parent_id").isNull()), inner).first()
    if trees != 1 or n < LIGHT_FROM:
        return answer_at(solve_vectors(tree, BISECTION, m, **options), tree, BISECTION)
    grid = options.get("finish", "grid") == "grid"
    # the estimate decides only what is tried first; with few leaves there are long paths
    parts = _raked_parts(tree, n, m) if grid and n - forking >= n // 4 else None
    if parts is not None and (found := _ranked_bisection(tree, parts, n, m)) is not None:
        return found
    ready = prepare_tree(tree, m, options.get("seed", 0), options.get("shape", "balanced"), rules=options.get("rules", Rules()))
    tries = [lambda: _light_bisection(tree, ready, n, m, options)]
    if grid and parts is None:
        # either is exact; in a tree that forks often, parts below the lightest edges are small
        forks, pieces = ready.dec.comp.agg(F.count_if(F.col("n_children") == 2), F.count(F.lit(1))).first()
        tries.insert(0 if 8 * forks >= pieces else 1, lambda: _ranked_bisection(tree, _ranked_parts(ready), n, m))
    for attempt in tries:
        if (found := attempt()) is not None:
            return found
    return answer_at(solve_vectors(ready, BISECTION, **options), tree, BISECTION)


def k_spanning(tree: DataFrame, k: int, sense: str = "min", m: int = 8, **options) -> DataFrame:
    problem = K_MIN if sense == "min" else K_MAX
    return answer_at(solve_vectors(tree, problem, m, most=max(0, k), **options), tree, problem, k)
