"""Merge schedule: which edges of a contracted tree are merged in which step.

The tree of pieces is cut again and again until single pieces are left; merging
goes the same way back. A step first cuts every part at its most balanced edge;
a part that then touches more than three cut edges is cut once more so that each
half touches three at most. So parts shrink geometrically and their border
stays constant, whatever the depth of the tree.

A part of degree at most three has an edge whose removal leaves at most
(2n+1)/3 on a side: walk from any piece towards the side that holds more than
half. And among four border edges some edge parts them two and two: at a piece
whose branches hold at most one each there would be more than three of them.
"""

from __future__ import annotations


import pyarrow as pa
from pyspark.sql import DataFrame

from .iterate import prepare

SCHEDULE = "tree_id long, step int, half int, child_comp long, left_part long, right_part long, out_part long"
MAX_BORDER = 3


class Part:
    """A connected set of pieces, with the number of already cut edges at each."""

    def __init__(self, nodes: list[int], parent: dict[int, int], cut: dict[int, int]):
        self.nodes, self.parent, self.cut = nodes, parent, cut

    def border(self) -> int:
        return sum(self.cut.get(v, 0) for v in self.nodes)

    def sums(self, weight) -> tuple[dict[int, int], list[int]]:
        """Weight below each piece inside the part, and the pieces in an order with parents first."""
        inside = set(self.nodes)
        kids: dict[int, list[int]] = {v: [] for v in self.nodes}
        root = None
        for v in self.nodes:
            p = self.parent.get(v)
            if p in inside:
                kids[p].append(v)
            else:
                root = v
        order = [root]
        for v in order:
            order += kids[v]
        below = {v: weight(v) for v in self.nodes}
        for v in reversed(order[1:]):
            below[self.parent[v]] += below[v]
        return below, order

    def split_at(self, child: int) -> tuple[Part, Part]:
        """Cuts the edge above child: (upper part, lower part)."""
        inside = set(self.nodes)
        kids: dict[int, list[int]] = {}
        for v in self.nodes:
            p = self.parent.get(v)
            if p in inside:
                kids.setdefault(p, []).append(v)
        low = [child]
        for v in low:
            low += kids.get(v, [])
        low_set = set(low)
        self.cut[child] = self.cut.get(child, 0) + 1
        top = self.parent[child]
        self.cut[top] = self.cut.get(top, 0) + 1
        return Part([v for v in self.nodes if v not in low_set], self.parent, self.cut), Part(low, self.parent, self.cut)


def balance_edge(part: Part) -> int:
    below, order = part.sums(lambda _: 1)
    n = len(part.nodes)
    return min(order[1:], key=lambda v: (max(below[v], n - below[v]), v))


def border_edge(part: Part) -> int | None:
    """An edge with two of the part's cut edges on each side (needed at four, which has one)."""
    below, order = part.sums(lambda v: part.cut.get(v, 0))
    total = part.border()
    good = [v for v in order[1:] if below[v] >= 2 and total - below[v] >= 2]
    return min(good) if good else None


def build_plan(parents: dict[int, int | None]) -> list[tuple[int, int, int, int, int, int]]:
    """(step, half, child_comp, left_part, right_part, out_part) of one tree, in merge order.

    A part is named after its topmost piece at the time it exists; step 1 merges what the last cut parted.
    """
    parent = {v: p for v, p in parents.items() if p is not None}
    root = next(v for v, p in parents.items() if p is None)
    parts, cuts, step = [Part(list(parents), parent, {})], [], 0
    tops = {id(parts[0]): root}
    while any(len(p.nodes) > 1 for p in parts):
        after = []
        for part in parts:
            if len(part.nodes) == 1:
                after.append(part)
                continue
            top = tops[id(part)]
            e = balance_edge(part)
            upper, lower = part.split_at(e)
            cuts.append((step, 2, e, top, e, top))
            tops[id(upper)], tops[id(lower)] = top, e
            for side in (upper, lower):
                if side.border() > MAX_BORDER and len(side.nodes) > 1:
                    f = border_edge(side)
                    u2, l2 = side.split_at(f)
                    t2 = tops[id(side)]
                    cuts.append((step, 1, f, t2, f, t2))
                    tops[id(u2)], tops[id(l2)] = t2, f
                    after += [u2, l2]
                else:
                    after.append(side)
        parts = after
        # ids of dead objects may come again: keep only the live ones' names
        tops = {id(p): tops[id(p)] for p in parts}
        step += 1
    return sorted(((step - s, half, child, left, right, out) for s, half, child, left, right, out in cuts), key=lambda c: (c[0], c[1], c[2]))


def build(comp: DataFrame) -> DataFrame:
    """SCHEDULE of every tree of pieces; a tree's plan is made in one task (about 14 m rows)."""
    prepare(comp.sparkSession)

    def run(table: pa.Table) -> pa.Table:
        parents = dict(zip(table["comp_id"].to_pylist(), table["parent_comp"].to_pylist()))
        plan = build_plan(parents)
        tree = table["tree_id"][0].as_py()
        columns = list(zip(*plan)) if plan else [[]] * 6
        types = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64()]
        return pa.table([pa.array([tree] * len(plan), pa.int64()), *[pa.array(list(c), t) for c, t in zip(columns, types)]], ["tree_id", "step", "half", "child_comp", "left_part", "right_part", "out_part"])

    return comp.select("tree_id", "comp_id", "parent_comp").groupBy("tree_id").applyInArrow(run, SCHEDULE)


def steps_of(schedule: DataFrame) -> list[tuple[int, int]]:
    """The merge turns in order, as (step, half); a logarithmic number."""
    return sorted((r["step"], r["half"]) for r in schedule.select("step", "half").distinct().collect())


