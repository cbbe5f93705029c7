"""Decomposition of a binary tree into at most about 14 m connected pieces, by contraction in turns.

In a turn some components are selected (roots, those with two children, those
below a completed one, and by a coin those with one child); every other one is
merged into its closest selected ancestor. A component that has reached n/m
vertices is completed and merges no more.

The loop works on a component table that shrinks by a constant factor in each
turn; a turn is three jobs, whose measures come from the same passes. Completed
components leave the table: at most m ever do, so what the others need to know
of them is a small table. Once the table is no longer than one machine's space
(about n/m log n rows) it is finished in one task by the same rules on arrays,
with the same coins and so the same pieces. Trees smaller than a piece are whole pieces from
the start.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .iterate import materialise, measured, prepare, release

#: A machine's space is its share n/m times a logarithm: with this factor, and within these bounds
#: (the upper one is about 300 MB of arrays), it is how long a component table one task may finish.
LOCAL_FACTOR = 0.25
LOCAL_FLOOR, LOCAL_CEILING = 20_000, 4_000_000
#: Most completed components that are sent to all tasks; a larger m joins them by shuffle.
BROADCAST_COMPLETED = 200_000
#: Doublings of the first pass over walks; their plan doubles with each, and most walks are this short.
FIRST_DOUBLINGS = 2
COIN_SIDES = 1 << 20
#: From RANGES_FROM vertices on, where three in four have their parent's id within NEAR of theirs, turns are first made inside
#: ranges of ids: RANGE_ROWS vertices each, at most MOST_RANGES ranges.
RANGES_FROM, RANGE_ROWS, NEAR, MOST_RANGES = 2_000_000, 250_000, 1 << 14, 512
#: The span of ids is laid out in so many cells, to look ranges up; from so many bounds in a cell on, ids are compared with all bounds.
CELLS, CELL_BOUNDS = 2048, 4


@dataclass(frozen=True)
class Rules:
    """The selection rules; switching one off is an ablation."""

    root: bool = True
    two_children: bool = True
    below_completed: bool = True
    coin: bool = True
    p: float = 0.5
    stop_factor: int = 14
    max_iterations: int = 200


@dataclass
class Decomposition:
    assign: DataFrame
    comp: DataFrame
    m: int
    n: int
    trees: int
    metrics: list[tuple[int, str, float]] = field(default_factory=list)
    #: whether comp is short enough to be sent to all tasks
    few: bool = False

    def measure(self, name: str) -> list[float]:
        return [v for _, k, v in self.metrics if k == name]

    @property
    def iterations(self) -> int:
        return int(max([0, *self.measure("iterations")]))


# ---- the coin, one definition for both forms ----

# The primes of the public XXH64 function, which Spark's xxhash64 is.
_PRIMES = (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5)
# End of fixed values.
_SPARK_SEED = 42


def _rotate(x: np.ndarray, by: int) -> np.ndarray:
    return (x << np.uint64(by)) | (x >> np.uint64(64 - by))


def hash_long(value: np.ndarray, seed: np.ndarray) -> np.ndarray:
    """XXH64 of one 64-bit number for each seed, as Spark computes it for a bigint column."""
    one, two, three, four, five = (np.uint64(p) for p in _PRIMES)
    h = seed + five + np.uint64(8)
    h = h ^ (_rotate(value * two, 31) * one)
    h = _rotate(h, 27) * one + four
    for shift, prime in ((33, two), (29, three)):
        h = (h ^ (h >> np.uint64(shift))) * prime
    return h ^ (h >> np.uint64(32))


def coins(tree: np.ndarray, comp: np.ndarray, turn: int, seed: int) -> np.ndarray:
    """What coin() gives, on arrays."""
    with np.errstate(over="ignore"):
        h = np.full(len(comp), _SPARK_SEED, np.uint64)
        for part in (tree, comp, np.full(len(comp), turn), np.full(len(comp), seed)):
            h = hash_long(part.astype(np.int64).view(np.uint64), h)
    return (h & np.uint64(COIN_SIDES - 1)).astype(np.int64)


def coin(turn: int, seed: int):
    """A seeded hash, never rand(): a recomputed task must choose alike."""
    return F.pmod(F.xxhash64("tree_id", "comp_id", F.lit(turn).cast("long"), F.lit(seed).cast("long")), F.lit(COIN_SIDES))


# ---- turns on arrays (also the sequential form of the algorithm) ----


def contract_arrays(
    tree: np.ndarray, node_id: np.ndarray, parent: np.ndarray, size: np.ndarray, limit: float, stop: int, seed: int, rules: Rules = Rules(), completed: np.ndarray | None = None, gone_kids: np.ndarray | None = None, first_turn: int = 0
) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[tuple[int, str, float]]]:
    """All remaining turns on arrays; parent holds positions, -1 for roots.

    gone_kids counts children that are completed and not among the positions' parents' children here.
    Returns (position of the component each position ends in, sizes by position, completed by position, metrics).
    """
    n = len(node_id)
    up, size = parent.copy(), size.astype(np.int64).copy()
    done = np.zeros(n, bool) if completed is None else completed.copy()
    gone = np.zeros(n, np.int64) if gone_kids is None else gone_kids.astype(np.int64).copy()
    alive = np.ones(n, bool)
    into = np.arange(n)
    metrics: list[tuple[int, str, float]] = []
    turn = first_turn
    while int(alive.sum()) > stop and turn < rules.max_iterations:
        live = np.flatnonzero(alive)
        kids = np.bincount(up[live][up[live] >= 0], minlength=n) + gone
        chosen = np.zeros(n, bool)
        above = up[live]
        if rules.root:
            chosen[live] |= above < 0
        if rules.two_children:
            chosen[live] |= kids[live] == 2
        if rules.below_completed:
            chosen[live] |= (above >= 0) & done[np.maximum(above, 0)]
        if rules.coin:
            chosen[live] |= (kids[live] == 1) & (coins(tree[live], node_id[live], turn, seed) < int(rules.p * COIN_SIDES))
        # without the rule, walks pass completed components, and pieces need not be connected
        fixed = (chosen | done) if rules.below_completed else chosen.copy()
        fixed[live[above < 0]] = True
        moving = live[~fixed[live] & ~done[live]]
        active = live[~done[live]]
        metrics += [(turn, "components", len(live)), (turn, "selected_share", float(fixed[active].sum()) / max(1, len(active))), (turn, "merged", len(moving)), (turn, "max_children", float(kids[live].max(initial=0)))]
        if not len(moving):
            # a root is fixed whatever its coin
            if not np.any((kids[live] == 1) & ~done[live] & (above >= 0) & rules.coin):
                break  # nothing can merge any more
            turn += 1
            continue
        ptr = np.where(fixed, np.arange(n), up)
        hops = np.where(fixed, 0, 1)
        while True:
            far = ptr[moving]
            hops[moving] += hops[far]
            new = ptr[far]
            if np.array_equal(new, far):
                break
            ptr[moving] = new
        metrics.append((turn, "longest_walk", float(hops[moving].max())))
        target = ptr[moving]
        np.add.at(size, target, size[moving])
        np.add.at(gone, target, gone[moving])
        into[moving] = target
        alive[moving] = False
        rest = np.flatnonzero(alive)
        has = up[rest] >= 0
        up[rest[has]] = into[up[rest[has]]]
        done[rest] |= size[rest] >= limit
        turn += 1
    while True:
        new = into[into]
        if np.array_equal(new, into):
            break
        into = new
    metrics.append((turn, "iterations", turn))
    return into, size, done, metrics


# ---- the distributed loop ----

COMPONENT = ("tree_id", "comp_id", "parent_comp", "n_vertices", "below", "gone_kids")


def initial(bt: DataFrame) -> DataFrame:
    """One component for each vertex. below: the parent is completed; gone_kids: completed children."""
    return bt.select("tree_id", F.col("node_id").alias("comp_id"), F.col("parent_id").alias("parent_comp"), F.lit(1).cast("long").alias("n_vertices"), F.lit(False).alias("below"), F.lit(0).cast("long").alias("gone_kids"))


def select(comp: DataFrame, turn: int, seed: int, rules: Rules) -> DataFrame:
    """Adds kids and selected to the components of the loop."""
    counted = comp.where("parent_comp IS NOT NULL AND NOT below").groupBy("tree_id", F.col("parent_comp").alias("comp_id")).agg(F.count(F.lit(1)).alias("open_kids"))
    rows = comp.join(counted, ["tree_id", "comp_id"], "left").withColumn("kids", F.coalesce("open_kids", F.lit(0)) + F.col("gone_kids")).drop("open_kids")
    chosen = F.col("parent_comp").isNull() | F.col("below")
    if rules.two_children:
        chosen = chosen | (F.col("kids") == 2)
    if rules.coin:
        chosen = chosen | ((F.col("kids") == 1) & (coin(turn, seed) < int(rules.p * COIN_SIDES)))
    return rows.withColumn("selected", chosen)


def walks(rows: DataFrame) -> tuple[DataFrame, int]:
    """(tree_id, comp_id, target, n_vertices, gone_kids) of every unselected component, and the longest walk.

    Pointer doubling among the unselected ones. After d doublings a pointer has gone
    2^d steps or has arrived before, so passes end when none has gone all of them.
    """
    now = rows.where("NOT selected").select("tree_id", "comp_id", F.col("parent_comp").alias("target"), F.lit(1).cast("long").alias("hops"), "n_vertices", "gone_kids")
    done, steps = 0, FIRST_DOUBLINGS
    while True:
        before = now
        for _ in range(steps):
            ahead = now.select("tree_id", F.col("comp_id").alias("target"), F.col("target").alias("far"), F.col("hops").alias("more"))
            now = now.join(ahead, ["tree_id", "target"], "left").select("tree_id", "comp_id", F.coalesce("far", "target").alias("target"), (F.col("hops") + F.coalesce("more", F.lit(0))).alias("hops"), "n_vertices", "gone_kids")
        done, steps = done + steps, 1
        now, seen = measured(now, "walk", longest=F.max("hops"))
        release(before)
        if int(seen["longest"] or 0) < 1 << done:
            return now, int(seen["longest"] or 0)


def contract(rows: DataFrame, targets: DataFrame, limit: float) -> DataFrame:
    """The selected components after the merges: sizes added up, parents relinked."""
    sums = targets.groupBy("tree_id", F.col("target").alias("comp_id")).agg(F.sum("n_vertices").alias("more"), F.sum("gone_kids").alias("more_gone"))
    moved_parent = targets.select("tree_id", F.col("comp_id").alias("parent_comp"), "target")
    left = rows.where("selected").select(*COMPONENT)
    size = F.col("n_vertices") + F.coalesce("more", F.lit(0))
    summed = left.join(sums, ["tree_id", "comp_id"], "left").withColumns({"n_vertices": size, "gone_kids": F.col("gone_kids") + F.coalesce("more_gone", F.lit(0))})
    linked = summed.join(moved_parent, ["tree_id", "parent_comp"], "left").withColumn("parent_comp", F.coalesce("target", "parent_comp"))
    return linked.select(*COMPONENT, (F.col("n_vertices") >= limit).alias("completed"))


def without_completed(after: DataFrame, m: int) -> DataFrame:
    """The loop's next table: completed components leave, and their parents and children learn of it.

    A completed component has n/m vertices at least, so there are at most m of them.
    """
    small = F.broadcast if m <= BROADCAST_COMPLETED else (lambda df: df)
    gone = after.where("completed")
    parents = gone.select("tree_id", F.col("comp_id").alias("parent_comp"), F.lit(True).alias("parent_gone"))
    kids = gone.where("parent_comp IS NOT NULL AND NOT below").groupBy("tree_id", F.col("parent_comp").alias("comp_id")).agg(F.count(F.lit(1)).alias("new_gone"))
    rows = after.where("NOT completed").join(small(parents), ["tree_id", "parent_comp"], "left").join(small(kids), ["tree_id", "comp_id"], "left")
    return rows.withColumns({"below": F.col("below") | F.coalesce("parent_gone", F.lit(False)), "gone_kids": F.col("gone_kids") + F.coalesce("new_gone", F.lit(0))}).select(*COMPONENT)


def _finish_locally(limit: float, stop: int, seed: int, rules: Rules, turn: int):
    schema = "tree_id long, comp_id long, target long, n_vertices long, completed boolean, metric string, at int, value double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        if not held:
            return
        table = pa.Table.from_batches(held)
        tree, node = table["tree_id"].to_numpy(), table["comp_id"].to_numpy()
        above = table["parent_comp"].fill_null(-1).to_numpy()
        order = np.lexsort((node, tree))
        tree, node, above = tree[order], node[order], above[order]
        size, gone, done = table["n_vertices"].to_numpy()[order], table["gone_kids"].to_numpy()[order], np.asarray(table["completed"].to_numpy(zero_copy_only=False), bool)[order]
        parent = positions(tree, node, above)
        into, size, done, metrics = contract_arrays(tree, node, parent, size, limit, stop, seed, rules, done, gone, turn)
        n = len(node)
        none = pa.nulls(n, pa.string()), pa.nulls(n, pa.int32()), pa.nulls(n, pa.float64())
        names = [f.split(" ")[0] for f in schema.split(", ")]
        yield pa.RecordBatch.from_arrays([pa.array(tree), pa.array(node), pa.array(node[into]), pa.array(size), pa.array(done), *none], names)
        k = len(metrics)
        blank = [pa.nulls(k, t) for t in (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.bool_())]
        yield pa.RecordBatch.from_arrays([*blank, pa.array([x[1] for x in metrics]), pa.array([x[0] for x in metrics], pa.int32()), pa.array([float(x[2]) for x in metrics])], names)

    return run, schema


class Unchecked(ValueError):
    """Whether all vertices have two children at most has to be found out by other means."""


def near_ids(most: int = MOST_RANGES) -> dict:
    """What turns inside ranges have to know of all vertices, as aggregates over node_id and parent_id; bounds: `most` quantiles of the ids."""
    quantiles = F.percentile_approx("node_id", [i / most for i in range(1, most)] or [0.5])
    return {"near": F.count_if(F.abs(F.col("node_id") - F.col("parent_id")) <= NEAR), "least": F.min("node_id"), "largest": F.max("node_id"), "bounds": quantiles}


def range_lookup(bounds: list[int], least: int, largest: int):
    """Column of an id -> number of bounds (ascending) at or below it.

    Comparisons with every bound are more than the JVM compiles, so the bounds are looked up by cells of the span of ids.
    """
    width = (largest - least) // CELLS + 1
    inside: list[list[int]] = [[] for _ in range(CELLS)]
    for b in bounds:
        inside[min(max(b - least, 0) // width, CELLS - 1)].append(b)
    deep = max(map(len, inside))
    if deep >= CELL_BOUNDS or largest - least >= 1 << 62:
        return lambda id_: sum((F.col(id_) >= b).cast("int") for b in bounds)
    before = np.cumsum([0, *map(len, inside)])[:-1].tolist()

    def listed(values: list[int], cell):
        # one literal after constant folding
        return F.get(F.expr(f"cast(split('{','.join(map(str, values))}', ',') AS array<bigint>)"), cell)

    def of(id_: str):
        cell = F.expr(f"cast((least(greatest({id_}, {least}L), {largest}L) - ({least}L)) div {width}L AS int)")
        at = listed(before, cell)
        for j in range(deep):
            at = at + (F.col(id_) >= listed([x[j] if j < len(x) else (1 << 63) - 1 for x in inside], cell)).cast("int")
        return at.cast("int")

    return of


def _inside_ranges(n: int, limit: float, stop: int, seed: int, rules: Rules):
    """Turns inside one range of ids. Rows with hangs stand for children in other ranges, which never merge here, as if completed.

    No turns are made where a vertex has more than two children.
    """
    schema = "tree_id long, comp_id long, target long, parent_id long, n_vertices long, completed boolean, turns int, walk int, kids int"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        if not held:
            return
        table = pa.Table.from_batches(held)
        del held
        tree, node, above = (table[c].fill_null(-1).to_numpy() for c in ("tree_id", "node_id", "parent_id"))
        hangs = np.asarray(table["hangs"].to_numpy(zero_copy_only=False), bool)
        del table
        # children elsewhere come right behind the vertex they hang at
        order = np.lexsort((hangs, node, tree))
        tree, node, above, hangs = tree[order], node[order], above[order], hangs[order]
        gone = np.bincount(np.cumsum(~hangs)[hangs] - 1, minlength=int((~hangs).sum()))
        tree, node, above = tree[~hangs], node[~hangs], above[~hangs]
        parent = positions(tree, node, above)
        degree = np.bincount(parent[parent >= 0], minlength=len(node)) + gone
        turns = rules if degree.max(initial=0) <= 2 else replace(rules, max_iterations=0)
        into, size, done, metrics = contract_arrays(tree, node, parent, np.ones(len(node), np.int64), limit, max(1, stop * len(node) // n), seed, turns, None, gone)
        metrics.append((0, "max_children", int(degree.max(initial=0))))
        top = into == np.arange(len(node))
        most = {k: int(max((v for _, name, v in metrics if name == k), default=0)) for k in ("iterations", "longest_walk", "max_children")}
        columns = [tree, node, node[into], pa.array(above, mask=~top | (above < 0)), pa.array(size, mask=~top), pa.array(done, mask=~top)]
        names = [f.split(" ")[0] for f in schema.split(", ")]
        yield pa.RecordBatch.from_arrays([*map(pa.array, columns[:3]), *columns[3:], *(pa.array(np.full(len(node), v, np.int32)) for v in most.values())], names)

    return run, schema


def within_ranges(bt: DataFrame, n: int, limit: float, stop: int, seed: int, rules: Rules, seen: dict | None = None) -> tuple[DataFrame, DataFrame, dict] | None:
    """Turns inside ranges of ids, all ranges at once: (vertex to component, components, measures). None: too few parents have near ids.

    Components at the top of a range count as selected, so pieces stay connected with two children at most.
    seen: near_ids() of the vertices, where these are known.
    """
    parts = min(MOST_RANGES, -(-n // RANGE_ROWS))
    if seen is None:
        seen = bt.agg(*[c.alias(k) for k, c in near_ids(parts).items()]).first().asDict()
    if 4 * seen["near"] < 3 * n:
        return None
    quantiles = seen["bounds"]
    bounds = sorted({quantiles[min(i * (len(quantiles) + 1) // parts, len(quantiles)) - 1] for i in range(1, parts)} or set(quantiles[:1]))
    range_of = range_lookup(bounds, seen["least"], seen["largest"])
    rows = bt.select("tree_id", "node_id", "parent_id", F.lit(False).alias("hangs"), range_of("node_id").alias("range"))
    across = rows.withColumn("above", range_of("parent_id")).where("above <> range").select("tree_id", F.col("parent_id").alias("node_id"), F.lit(None).cast("long").alias("parent_id"), F.lit(True).alias("hangs"), F.col("above").alias("range"))
    run, schema = _inside_ranges(n, limit, stop, seed, rules)
    is_top = F.col("comp_id") == F.col("target")
    counts = {"alive": F.count_if(is_top), "completed": F.count_if("completed"), "turns": F.max("turns"), "longest_walk": F.max("walk"), "max_children": F.max("kids")}
    dealt = rows.unionAll(across).repartitionById(len(bounds) + 1, F.col("range"))
    log, got = measured(dealt.mapInArrow(run, schema), "ranges", **counts)
    tops = log.where(is_top).select("tree_id", "comp_id", "parent_id", "n_vertices", "completed")
    few = F.broadcast if got["alive"] <= BROADCAST_COMPLETED else (lambda df: df)
    asked = few(tops.where("parent_id IS NOT NULL").select("tree_id", F.col("parent_id").alias("node_id")).distinct())
    above = log.select("tree_id", F.col("comp_id").alias("node_id"), F.col("target").alias("parent_comp")).join(asked, ["tree_id", "node_id"]).withColumnRenamed("node_id", "parent_id")
    after = tops.join(few(above), ["tree_id", "parent_id"], "left").select("tree_id", "comp_id", "parent_comp", "n_vertices", F.lit(False).alias("below"), F.lit(0).cast("long").alias("gone_kids"), "completed", F.col("parent_id").alias("attach_node"))
    return log, materialise(after, "components"), got


def positions(tree: np.ndarray, node: np.ndarray, above: np.ndarray) -> np.ndarray:
    """Row of each parent in arrays sorted by (tree, node); -1 for none (negative) or absent ones."""
    if not len(node):
        return np.zeros(0, np.int64)
    _, code = np.unique(tree, return_inverse=True)
    ids = np.unique(node)
    key = code.astype(np.int64) * len(ids) + np.searchsorted(ids, node)
    want = np.searchsorted(ids, above)
    known = (above >= 0) & (ids[np.minimum(want, len(ids) - 1)] == above)
    look = code.astype(np.int64) * len(ids) + np.minimum(want, len(ids) - 1)
    at = np.searchsorted(key, look)
    at = np.minimum(at, len(key) - 1)
    return np.where(known & (key[at] == look), at, -1)


def local_space(n: int, m: int) -> int:
    """How many rows one task may finish: n/m times a quarter of log2 n (within LOCAL_FLOOR and LOCAL_CEILING)."""
    return min(LOCAL_CEILING, max(LOCAL_FLOOR, math.ceil(LOCAL_FACTOR * max(1.0, n / max(1, m)) * math.log2(max(2, n)))))


def decompose(bt: DataFrame, m: int, seed: int = 0, rules: Rules = Rules(), local_rows: int | None = None, whole_trees: bool = True, known: dict | None = None) -> Decomposition:
    """Pieces of a binary forest: ASSIGN (vertex -> component) and COMP (the contracted tree).

    local_rows: component tables of at most so many rows are finished in one task; None
    takes what one machine may hold, n/m times a quarter of log2 n (within LOCAL_FLOOR
    and LOCAL_CEILING), 0 keeps everything in the distributed loop. The pieces are the same either way. whole_trees: trees below n/m
    vertices are whole pieces at once. Raises where the turns run out with too many pieces.
    known: n and near_ids() of a single tree whose degrees nobody has looked at; raises Unchecked unless turns inside
    ranges, which see every vertex with all its children, show that no vertex has more than two.
    """
    spark = bt.sparkSession
    prepare(spark)
    bt = bt.select("tree_id", "node_id", "parent_id")
    if known is None:
        per_tree, found = measured(
            bt.groupBy("tree_id").agg(F.count(F.lit(1)).alias("n"), F.min(F.when(F.col("parent_id").isNull(), F.col("node_id"))).alias("root")), "tree-sizes", n=F.coalesce(F.sum("n"), F.lit(0)), trees=F.count(F.lit(1))
        )
        n, trees = int(found["n"] or 0), int(found["trees"])
    else:
        per_tree, n, trees = None, known["n"], 1
    limit = max(1.0, n / max(1, m))
    by_the_book = rules.root and rules.two_children and rules.below_completed and rules.coin
    ranges = local_rows is None and by_the_book
    if local_rows is None:
        local_rows = local_space(n, m)
    stop = rules.stop_factor * m + trees
    metrics: list[tuple[int, str, float]] = []
    whole, rest, rows_now = None, bt, n
    if whole_trees and trees > 1:
        small = per_tree.where(F.col("n") <= limit)
        whole = bt.join(small.select("tree_id", "root"), "tree_id").select("tree_id", "node_id", F.col("root").alias("comp_id"))
        rest = bt.join(small.select("tree_id"), "tree_id", "left_anti")
        n_small, covered = small.agg(F.count(F.lit(1)), F.coalesce(F.sum("n"), F.lit(0))).first()
        stop -= n_small
        rows_now = n - covered
    comp = initial(rest)
    frozen: list[DataFrame] = []
    logs: list[DataFrame] = []
    held: list[DataFrame] = [per_tree]
    turn, n_frozen, few, in_ranges = 0, 0, False, None
    if ranges and rows_now >= RANGES_FROM and rows_now > local_rows and (known is None or 4 * known["near"] >= 3 * n) and (got := within_ranges(rest, rows_now, limit, rules.stop_factor * m, seed, rules, known)):
        log, after, seen = got
        if known and seen["max_children"] > 2:
            release(log, after)
            raise Unchecked
        in_ranges = after
        metrics += [(0, "components", rows_now), (0, "selected_share", seen["alive"] / rows_now), (0, "merged", rows_now - seen["alive"])]
        metrics += [(0, k, seen[k]) for k in ("longest_walk", "max_children")]
        held += [log, after]
        logs.append(log.select("tree_id", "comp_id", "target"))
        if seen["completed"]:
            frozen.append(after.where("completed"))
        n_frozen, rows_now = seen["completed"], seen["alive"] - seen["completed"]
        comp = without_completed(after, m)
        # coins of turns that have been are not thrown again
        turn, few = seen["turns"], seen["alive"] <= BROADCAST_COMPLETED
    elif known:
        raise Unchecked
    while rows_now > local_rows and rows_now + n_frozen > stop and turn < rules.max_iterations:
        if not (rules.root and rules.below_completed):
            raise ValueError("the distributed loop needs the root rule and the rule below completed components")
        rows, seen = measured(select(comp, turn, seed, rules), "selected", selected=F.sum(F.col("selected").cast("long")), most=F.max("kids"))
        chosen = int(seen["selected"] or 0)
        metrics += [(turn, "components", rows_now + n_frozen), (turn, "selected_share", chosen / rows_now), (turn, "merged", rows_now - chosen), (turn, "max_children", seen["most"] or 0)]
        held.append(rows)
        if chosen == rows_now:
            if not rules.coin:
                break
            turn += 1
            continue
        targets, walk = walks(rows)
        metrics.append((turn, "longest_walk", walk))
        logs.append(rows.where("selected").select("tree_id", "comp_id", F.col("comp_id").alias("target")).unionAll(targets.select("tree_id", "comp_id", "target")))
        after, seen = measured(contract(rows, targets, limit), "components", completed=F.sum(F.col("completed").cast("long")), alive=F.count(F.lit(1)))
        held.append(after)
        left = int(seen["completed"] or 0)
        if left:
            frozen.append(after.where("completed"))
        n_frozen, rows_now = n_frozen + left, int(seen["alive"]) - left
        comp = without_completed(after, m) if left else after.select(*COMPONENT)
        turn += 1
    if rows_now + n_frozen > stop and turn < rules.max_iterations and rows_now <= local_rows:
        run, schema = _finish_locally(limit, stop, seed, rules, turn)
        table = comp.select("tree_id", "comp_id", "parent_comp", "n_vertices", "gone_kids", F.lit(False).alias("completed"))
        for part in frozen:
            # completed ones come along, for the rule below them and for the stop; their parents know of them already
            table = table.unionAll(part.select("tree_id", "comp_id", F.lit(None).cast("long"), "n_vertices", "gone_kids", F.lit(True)))
        finished = materialise(table.coalesce(1).mapInArrow(run, schema), "finished")
        held.append(finished)
        metrics += [(r["at"], r["metric"], r["value"]) for r in finished.where("metric IS NOT NULL").select("at", "metric", "value").collect()]
        last = finished.where("metric IS NULL").select("tree_id", "comp_id", "target")
    else:
        metrics.append((turn, "iterations", turn))
        last = None
    pieces = last.select("tree_id", "target").distinct().count() if last is not None else rows_now + n_frozen
    if by_the_book and pieces > stop:
        raise RuntimeError(f"{pieces} pieces after {rules.max_iterations} turns, more than {stop}")
    # components of ranges are few and what comes of them is no more, so it may go to all tasks
    assign, short = assignments(rest, logs, last, few), few
    if whole is not None:
        assign = assign.unionAll(whole)
    assign = materialise(assign, "assign")
    few = pieces + (n_small if whole is not None else 0) <= BROADCAST_COMPLETED
    if in_ranges is not None:
        comp_table = contracted_components(in_ranges, assignments(rest, logs[1:], last, short) if logs[1:] or last is not None else None, limit)
    else:
        comp_table = contracted_tree(bt, assign, limit, few)
    if whole is not None and in_ranges is not None:
        comp_table = comp_table.unionByName(contracted_tree(bt, whole, limit, few))
    comp_table = materialise(comp_table, "contracted")
    release(*held)
    return Decomposition(assign, comp_table, m, n, trees, metrics, few)


def trace(bt: DataFrame, m: int, seed: int = 0, rules: Rules = Rules()) -> list[tuple[int, int, int, int, str]]:
    """(turn, tree_id, comp_id, vertices, mark) of every component at the start of every turn of a small forest.

    mark is 'selected', 'merged' or 'completed', after the last turn 'left': the pictures one would draw of the turns.
    """
    n, trees = bt.count(), bt.where("parent_id IS NULL").count()
    limit, stop = max(1.0, n / max(1, m)), rules.stop_factor * m + trees
    comp, done, out = initial(bt), [], []
    for turn in range(rules.max_iterations):
        rows = materialise(select(comp, turn, seed, rules), "traced")
        here = rows.select("tree_id", "comp_id", "n_vertices", "selected").collect()
        if len(here) + len(done) <= stop:
            out += [(turn, *r[:3], "left") for r in here] + [(turn, *r, "completed") for r in done]
            break
        out += [(turn, *r[:3], "selected" if r[3] else "merged") for r in here] + [(turn, *r, "completed") for r in done]
        after = materialise(contract(rows, walks(rows)[0], limit), "traced")
        done += [tuple(r) for r in after.where("completed").select("tree_id", "comp_id", "n_vertices").collect()]
        comp = without_completed(after, m)
    return sorted(out)


def assignments(bt: DataFrame, logs: list[DataFrame], last: DataFrame | None, few: bool = False) -> DataFrame:
    """Where every vertex ends: the logs of the turns composed backwards, one join each, earlier ones larger.

    A component that a later log does not have was completed before, and stays. few: all but the first log are short.
    """
    final = last
    for log in reversed(logs):
        if final is None:
            final = log
            continue
        ends = final.select("tree_id", F.col("comp_id").alias("target"), F.col("target").alias("end"))
        final = log.join(F.broadcast(ends) if few else ends, ["tree_id", "target"], "left").select("tree_id", "comp_id", F.coalesce("end", "target").alias("target"))
    if final is None:
        return bt.select("tree_id", "node_id", F.col("node_id").alias("comp_id"))
    return final.select("tree_id", F.col("comp_id").alias("node_id"), F.col("target").alias("comp_id"))


def contracted_tree(bt: DataFrame, assign: DataFrame, limit: float, few: bool = False) -> DataFrame:
    """COMP from the assignment: parents, attach vertices, sizes, child counts. few: the pieces may go to all tasks."""
    small = F.broadcast if few else (lambda df: df)
    inside = assign.groupBy("tree_id", "comp_id").agg(F.count(F.lit(1)).alias("n_vertices"))
    roots = bt.join(small(assign.where("node_id = comp_id")), ["tree_id", "node_id"]).select("tree_id", "comp_id", F.col("parent_id").alias("attach_node"))
    # few rows are wanted of the whole assignment, so the small side may go to all tasks
    attach = small(roots.where("attach_node IS NOT NULL").select("tree_id", "attach_node").distinct())
    above = assign.select("tree_id", F.col("node_id").alias("attach_node"), F.col("comp_id").alias("parent_comp")).join(attach, ["tree_id", "attach_node"])
    linked = roots.join(above, ["tree_id", "attach_node"], "left")
    kids = linked.where("parent_comp IS NOT NULL").groupBy("tree_id", F.col("parent_comp").alias("comp_id")).agg(F.count(F.lit(1)).cast("int").alias("n_children"))
    return (
        inside.join(linked, ["tree_id", "comp_id"])
        .join(kids, ["tree_id", "comp_id"], "left")
        .select("tree_id", "comp_id", "parent_comp", "attach_node", "n_vertices", F.coalesce("n_children", F.lit(0)).alias("n_children"), (F.col("n_vertices") >= limit).alias("completed"))
    )


def contracted_components(after: DataFrame, ends: DataFrame | None, limit: float) -> DataFrame:
    """COMP from the components of ranges alone, each with the vertex it hangs at, and from where they end (None: where they are)."""
    rows = after.select("tree_id", "comp_id", "parent_comp", "attach_node", "n_vertices")
    if ends is None:
        placed = rows.withColumn("piece", F.col("comp_id"))
    else:
        into = ends.select("tree_id", F.col("node_id").alias("comp_id"), F.col("comp_id").alias("end"))
        above = ends.select("tree_id", F.col("node_id").alias("parent_comp"), F.col("comp_id").alias("parent_end"))
        placed = rows.join(into, ["tree_id", "comp_id"], "left").join(above, ["tree_id", "parent_comp"], "left")
        placed = placed.select("tree_id", "comp_id", F.coalesce("parent_end", "parent_comp").alias("parent_comp"), "attach_node", "n_vertices", F.coalesce("end", "comp_id").alias("piece"))
    inside = placed.groupBy("tree_id", F.col("piece").alias("comp_id")).agg(F.sum("n_vertices").alias("n_vertices"))
    linked = placed.where("comp_id = piece").select("tree_id", "comp_id", "parent_comp", "attach_node")
    kids = linked.where("parent_comp IS NOT NULL").groupBy("tree_id", F.col("parent_comp").alias("comp_id")).agg(F.count(F.lit(1)).cast("int").alias("n_children"))
    return (
        inside.join(linked, ["tree_id", "comp_id"])
        .join(kids, ["tree_id", "comp_id"], "left")
        .select("tree_id", "comp_id", "parent_comp", "attach_node", "n_vertices", F.coalesce("n_children", F.lit(0)).alias("n_children"), (F.col("n_vertices") >= limit).alias("completed"))
    )


def default_machines(n: int, piece: int = 20_000) -> int:
    """As many machines as give pieces of about `piece` vertices."""
    return max(1, math.ceil(n / piece))
