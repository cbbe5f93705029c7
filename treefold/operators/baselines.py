"""The simple methods the engine is judged against."""

from __future__ import annotations

import itertools
import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import NEG
from ..plans.decompose import positions
from ..plans.iterate import materialise, prepare
from .finite import Tables, _sorted_runs, fold
from .problems import Problem

ANSWER = "tree_id long, problem string, param long, value long, feasible boolean"
#: The sequential form gathers small trees to so many rows, and holds a tree of more rows than HELD_ROWS in a file.
RUN_ROWS, HELD_ROWS = 200_000, 2_000_000
#: Rows of such a file, or of a level, that are worked on at once.
CHUNK_ROWS = 500_000


def _answer_batch(trees, name, values, params=None) -> pa.RecordBatch:
    n = len(trees)
    return pa.RecordBatch.from_arrays(
        [pa.array(trees, pa.int64()), pa.array([name] * n), pa.array(params if params is not None else [None] * n, pa.int64()), pa.array(values, pa.int64()), pa.array([v is not None for v in values])],
        ["tree_id", "problem", "param", "value", "feasible"],
    )


def tree_arrays(table: pa.Table):
    tree, node = table["tree_id"].to_numpy(), table["node_id"].to_numpy()
    order = np.lexsort((node, tree))
    tree, node = tree[order], node[order]
    parent = positions(tree, node, table["parent_id"].fill_null(-1).to_numpy()[order])
    return tree, node, parent, table["node_w"].fill_null(0).to_numpy()[order], table["edge_w"].fill_null(0).to_numpy()[order]


def tree_runs(batches: Iterator[pa.RecordBatch], rows: int, most: int) -> Iterator[tuple[pa.Table | None, Iterator[pa.RecordBatch] | None]]:
    """Sorted input as tables of whole trees, of about `rows` rows; a tree of more than `most` rows as a stream, to be read before the next is asked for."""
    source = (b for b in batches if b.num_rows)
    held: list[pa.RecordBatch] = []
    count = 0
    pending: list[pa.RecordBatch] = []

    def first(b: pa.RecordBatch) -> int:
        return b.column("tree_id")[0].as_py()

    def last(b: pa.RecordBatch) -> int:
        return b.column("tree_id")[b.num_rows - 1].as_py()

    def one(tree: int, head: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        while head:
            yield head.pop(0)
        for batch in source:
            if last(batch) != tree:
                cut = int(np.argmin(batch.column("tree_id").to_numpy() == tree))
                pending.append(batch.slice(cut))
                if cut:
                    yield batch.slice(0, cut)
                return
            yield batch

    while (batch := pending.pop() if pending else next(source, None)) is not None:
        held.append(batch)
        count += batch.num_rows
        if count < rows:
            continue
        tree = last(batch)
        if first(held[0]) != tree:
            table = pa.Table.from_batches(held)
            cut = int(np.argmax(table["tree_id"].to_numpy() == tree))
            yield table.slice(0, cut).combine_chunks(), None
            held, count = table.slice(cut).to_batches(), table.num_rows - cut
        elif count > most:
            head, held, count = held, [], 0
            yield None, one(tree, head)
    if held:
        yield pa.Table.from_batches(held).combine_chunks(), None


def join_families(tables: Tables, up: np.ndarray, seen: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(parents, joint vector of each one's children): neighbours are joined in pairs, so a family of k takes log k passes."""
    order = np.argsort(up, kind="stable")
    up, seen = up[order], seen[order]
    while True:
        begins = np.flatnonzero(np.r_[True, up[1:] != up[:-1]])
        if len(begins) == len(up):
            return up, seen
        rank = np.arange(len(up)) - np.repeat(begins, np.diff(np.r_[begins, len(up)]))
        odd = np.flatnonzero(rank & 1)
        seen[odd - 1] = tables.joined(seen[odd - 1], seen[odd])
        keep = rank & 1 == 0
        up, seen = up[keep], seen[keep]


def fold_stream(tables: Tables, rows: Iterator[pa.RecordBatch]) -> list[int | None]:
    """Values of the roots of one tree, whose rows come sorted by parent.

    The rows go to a file of this task's own; memory holds the vertices that have children.
    """
    plain = lambda n: np.zeros(n, bool)
    with tempfile.TemporaryFile() as file:
        chunks: list[int] = []
        found: list[np.ndarray] = []
        for batch in rows:
            four = np.stack([batch.column("node_id").to_numpy(), *[batch.column(c).fill_null(f).to_numpy() for c, f in (("parent_id", -1), ("node_w", 0), ("edge_w", 0))]])
            above = four[1]
            new = above[np.r_[True, above[1:] != above[:-1]] & (above >= 0)]
            found.append(new[1:] if len(new) and found and len(found[-1]) and found[-1][-1] == new[0] else new)
            chunks.append(batch.num_rows)
            file.write(four.tobytes())
        inner = np.unique(np.concatenate(found))
        del found

        def passes() -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
            """(place among the inner vertices or -1, place of the parent or -1, weights) of about CHUNK_ROWS rows at a time."""
            file.seek(0)
            i = 0
            while i < len(chunks):
                parts, size = [], 0
                while i < len(chunks) and size < CHUNK_ROWS:
                    parts.append(np.frombuffer(file.read(32 * chunks[i]), np.int64).reshape(4, -1))
                    size += chunks[i]
                    i += 1
                node, above, node_w, edge_w = np.concatenate(parts, axis=1)
                at = np.minimum(np.searchsorted(inner, node), max(0, len(inner) - 1))
                at = np.where(inner[at] == node, at, -1) if len(inner) else np.full(len(node), -1)
                yield at, np.where(above >= 0, np.searchsorted(inner, above), -1), node_w, edge_w

        parent = np.full(len(inner), -2, np.int32)  # -1: a root, -2: no row of its own
        value = np.full((len(inner), tables.s, 1), NEG, np.int64)
        inner_w = np.zeros(len(inner), np.int64)
        for at, up, node_w, edge_w in passes():
            here = np.flatnonzero(at >= 0)
            parent[at[here]], inner_w[at[here]] = up[here], edge_w[here]
            value[at[here]] = tables.start(plain(len(here)), node_w[here], 1)
        absent = parent == -2
        parent[absent] = -1
        rooted = parent >= 0
        rooted[rooted] = ~absent[parent[rooted]]
        parent[~rooted] = -1
        del rooted
        out: list[int | None] = []

        def put(up: np.ndarray, vectors: np.ndarray, edge_w: np.ndarray) -> None:
            to, joint = join_families(tables, up, tables.lifted(vectors, plain(len(up)), edge_w))
            value[to] = tables.joined(value[to], joint)

        for at, up, node_w, edge_w in passes():
            leaf = np.flatnonzero(at < 0)
            alone = (up[leaf] < 0) | absent[up[leaf]] if len(inner) else np.ones(len(leaf), bool)
            leaf, single = leaf[~alone], leaf[alone]
            out += [tables.best(v[:, 0]) for v in tables.start(plain(len(single)), node_w[single], 1)]
            if len(leaf):
                put(up[leaf], tables.start(plain(len(leaf)), node_w[leaf], 1), edge_w[leaf])
    del inner
    # the inner vertices, deepest level first
    depth, far = (parent >= 0).astype(np.int32), parent.copy()
    while len(rest := np.flatnonzero(far >= 0)):
        more, further = depth[far[rest]], far[far[rest]]
        depth[rest] += more
        far[rest] = further
        del more, further, rest
    del far
    order = np.argsort(-depth, kind="stable").astype(np.int32)
    bounds = np.flatnonzero(np.diff(depth[order])) + 1
    del depth
    for a, b in itertools.pairwise([0, *bounds.tolist(), len(order)]):
        for c in range(a, b, CHUNK_ROWS):
            level = order[c : min(b, c + CHUNK_ROWS)]
            level = level[parent[level] >= 0]
            if len(level):
                put(parent[level], value[level], inner_w[level])
    return out + [tables.best(value[r, :, 0]) for r in np.flatnonzero((parent < 0) & ~absent)]


def sequential(tree: DataFrame, problem: Problem) -> DataFrame:
    """One machine folds a whole tree from the leaves; it holds small trees whole, and of a large one the vertices that have children."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = Tables(problem)
        for table, stream in tree_runs(batches, RUN_ROWS, HELD_ROWS):
            if stream is not None:
                first = next(stream)
                values = fold_stream(tables, itertools.chain([first], stream))
                yield _answer_batch([first.column("tree_id")[0].as_py()] * len(values), problem.name, values)
                continue
            trees, _, parent, node_w, edge_w = tree_arrays(table)
            value = fold(tables, parent, np.zeros(len(trees), bool), node_w, edge_w, np.zeros(0, np.int64), np.zeros((0, tables.s, 1), np.int64), 1)
            roots = np.flatnonzero(parent < 0)
            yield _answer_batch(trees[roots], problem.name, [tables.best(value[r, :, 0]) for r in roots])

    prepare(tree.sparkSession)
    rows = tree.select("tree_id", "node_id", "parent_id", "node_w", "edge_w").repartition("tree_id").sortWithinPartitions("tree_id", "parent_id")
    return rows.mapInArrow(run, ANSWER)


def depths(tree: DataFrame, max_depth: int = 100_000) -> tuple[DataFrame, int]:
    """(tree_id, node_id, depth) by pointer doubling, and the largest depth."""
    ptr = materialise(tree.select("tree_id", "node_id", F.col("parent_id").alias("ptr"), F.col("parent_id").isNotNull().cast("long").alias("depth")), "depth")
    while ptr.where("ptr IS NOT NULL").limit(1).count():
        far = ptr.select("tree_id", F.col("node_id").alias("ptr"), F.col("ptr").alias("next"), F.col("depth").alias("more"))
        ptr = materialise(ptr.join(far, ["tree_id", "ptr"], "left").select("tree_id", "node_id", F.col("next").alias("ptr"), (F.col("depth") + F.coalesce("more", F.lit(0))).alias("depth")), "depth")
    return ptr.select("tree_id", "node_id", "depth"), int(ptr.agg(F.max("depth")).first()[0] or 0)


def level_sync(tree: DataFrame, problem: Problem, max_levels: int = 200) -> DataFrame:
    """All vertices of a level in one round, deepest first; as many rounds as the tree is deep. Native column expressions only.

    Refuses trees deeper than max_levels: that many rounds is what the engine avoids.
    """
    t = Tables(problem)
    with_depth, deepest = depths(tree)
    if deepest > max_levels:
        raise ValueError(f"depth {deepest} needs as many rounds")
    rows = materialise(tree.join(with_depth, ["tree_id", "node_id"]), "levels")
    one = F.lit(1).cast("long")
    node_w = (one if problem.unit else F.col("node_w")) * t.sign
    edge_w = (one if problem.unit else F.coalesce("edge_w", F.lit(0))) * t.sign
    base = {i: F.lit(NEG) for i in range(t.s)}
    for state, weighted, factor in t.init:
        base[state] = node_w * factor if weighted else F.lit(t.sign * factor).cast("long")
    level_rows = None
    for level in range(deepest, -1, -1):
        here = rows.where(F.col("depth") == level).select("tree_id", "node_id", "parent_id", edge_w.alias("ew"), *[base[i].alias(f"v{i}") for i in range(t.s)])
        if level_rows is not None:
            seen = level_rows.select("tree_id", F.col("parent_id").alias("node_id"), F.struct(*[_lifted(t, b).alias(f"s{b}") for b in range(t.s)]).alias("kid"))
            # a family's vectors are folded in the order they come; joins are commutative and associative
            families = seen.groupBy("tree_id", "node_id").agg(F.collect_list("kid").alias("kids"))
            merged = here.join(families, ["tree_id", "node_id"], "left").withColumn("kids", F.coalesce("kids", F.expr("array()").cast(families.schema["kids"].dataType)))
            start = F.struct(*[F.col(f"v{i}").alias(f"s{i}") for i in range(t.s)])
            folded = F.aggregate("kids", start, lambda acc, kid: F.struct(*[_joined(t, acc, kid, c).alias(f"s{c}") for c in range(t.s)]))
            here = merged.withColumn("folded", folded).select("tree_id", "node_id", "parent_id", "ew", *[F.col(f"folded.s{i}").alias(f"v{i}") for i in range(t.s)])
        level_rows = materialise(here, "level")
    answers = F.greatest(*[F.col(f"v{i}") for i in t.final]) if len(t.final) > 1 else F.col(f"v{t.final[0]}")
    out = level_rows.withColumn("best", answers)
    if deepest:
        roots = tree.where("parent_id IS NULL").select("tree_id", "node_id")
        out = out.join(roots, ["tree_id", "node_id"])
    feasible = F.col("best") > NEG // 2
    return out.select("tree_id", F.lit(problem.name).alias("problem"), F.lit(None).cast("long").alias("param"), F.when(feasible, F.col("best") * t.sign).alias("value"), feasible.alias("feasible"))


def _lifted(t: Tables, b: int):
    options = [F.greatest(F.col(f"v{a}") + (F.col("ew") if weighted else F.lit(0)), F.lit(NEG)) for a, to, weighted in t.lift if to == b]
    return F.greatest(F.lit(NEG), *options) if options else F.lit(NEG)


def _joined(t: Tables, acc, kid, c: int):
    options = [acc[f"s{a}"] + kid[f"s{b}"] for a, b, to in t.join if to == c]
    return F.greatest(F.lit(NEG), *options) if options else F.lit(NEG)


def path_pieces(chain: DataFrame, problem: Problem, pieces: int = 8) -> DataFrame:
    """Equal cuts of a path: each piece becomes one summary, the summaries of a path are folded in order.

    Positions come from pointer doubling, so a path of any length needs a logarithmic number of joins.
    """
    with_depth, _ = depths(chain)
    rows = chain.join(with_depth, ["tree_id", "node_id"])
    sizes = rows.groupBy("tree_id").agg((F.max("depth") + 1).alias("n"))
    cut = rows.join(sizes, "tree_id").withColumn("piece", F.floor(F.col("depth") * pieces / F.col("n")).cast("int"))
    edges = cut.select("tree_id", "piece", "depth", "node_w", "edge_w")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = Tables(problem)
        for table in _sorted_runs(batches, ["tree_id", "piece"]):
            tree, piece, depth = table["tree_id"].to_numpy(), table["piece"].to_numpy(), table["depth"].to_numpy()
            order = np.lexsort((depth, piece, tree))
            tree, piece = tree[order], piece[order]
            node_w, edge_w = table["node_w"].fill_null(0).to_numpy()[order], table["edge_w"].fill_null(0).to_numpy()[order]
            start = np.flatnonzero(np.r_[True, (tree[1:] != tree[:-1]) | (piece[1:] != piece[:-1])])
            for a, b in zip(start, [*start[1:], len(tree)]):
                # value as seen from above the piece's top edge, for each state of what hangs below its last vertex
                value = np.full((1, t.s, t.s), NEG, np.int64)
                value[0, np.arange(t.s), np.arange(t.s)] = 0
                none = np.zeros(1, bool)
                for i in range(b - 1, a - 1, -1):
                    own = t.start(none, node_w[i : i + 1], t.s)
                    value = t.joined(own, value)
                    value = t.lifted(value, none, edge_w[i : i + 1]) if i > a or piece[a] else value
                yield pa.RecordBatch.from_arrays([pa.array(tree[a : a + 1]), pa.array(piece[a : a + 1].astype(np.int32)), pa.array([value[0].reshape(-1).tolist()], pa.list_(pa.int64()))], ["tree_id", "piece", "matrix"])

    matrices = edges.repartition("tree_id", "piece").sortWithinPartitions("tree_id", "piece").mapInArrow(run, "tree_id long, piece int, matrix array<long>")

    def join(table: pa.Table) -> pa.Table:
        t = Tables(problem)
        rows_ = sorted(table.to_pylist(), key=lambda r: -r["piece"])
        neutral = None
        for r in rows_:
            matrix = np.array(r["matrix"], np.int64).reshape(t.s, t.s)
            if neutral is None:  # nothing hangs below the last vertex: its accumulator is what a childless vertex would be joined with
                value = _without_child(t, matrix)
                neutral = True
            else:
                value = np.maximum(matrix + value[None, :], NEG).max(axis=1)
        return pa.Table.from_batches([_answer_batch([rows_[0]["tree_id"]], problem.name, [t.best(value)])])

    prepare(chain.sparkSession)
    return matrices.groupBy("tree_id").applyInArrow(join, ANSWER)


def _without_child(t: Tables, matrix: np.ndarray) -> np.ndarray:
    """The column of the state that changes nothing when joined in (each problem here has one, found from its join table)."""
    joins = {(a, b): c for a, b, c in t.join}
    neutral = [e for e in range(t.s) if all(joins.get((a, e)) == a for a, *_ in t.init)]
    if neutral:
        return matrix[:, neutral[0]]
    # label problems join a state with itself: nothing below means any of the states a vertex may start in
    return matrix[:, [a for a, *_ in t.init]].max(axis=1)


def random_cuts(bt: DataFrame, m: int, seed: int = 0, kind: str = "edge") -> DataFrame:
    """Pieces left by m random cuts: (tree_id, comp_id, n_vertices, is_root). The root's piece stays huge."""
    n = bt.count()
    share = F.pmod(F.xxhash64("node_id", F.lit(seed)), F.lit(1 << 30)) < int(min(1.0, m / max(1, n)) * (1 << 30))
    cut = share if kind == "edge" else F.lit(False)
    rows = bt.select("tree_id", "node_id", "parent_id", share.alias("hit"))
    if kind == "vertex":
        hit = rows.select("tree_id", F.col("node_id").alias("parent_id"), F.col("hit").alias("parent_hit"))
        rows = rows.join(hit, ["tree_id", "parent_id"], "left")
        cut = F.coalesce("hit", F.lit(False)) | F.coalesce("parent_hit", F.lit(False))
    else:
        cut = F.col("hit")
    ptr = materialise(rows.select("tree_id", "node_id", F.when(F.col("parent_id").isNull() | cut, F.col("node_id")).otherwise(F.col("parent_id")).alias("ptr")), "cuts")
    while True:
        nxt = ptr.select("tree_id", F.col("node_id").alias("ptr"), F.col("ptr").alias("far"))
        after = materialise(ptr.join(nxt, ["tree_id", "ptr"]).select("tree_id", "node_id", F.col("far").alias("ptr"), (F.col("far") != F.col("ptr")).alias("moved")), "cuts")
        if not after.where("moved").limit(1).count():
            break
        ptr = after.drop("moved")
    roots = bt.where("parent_id IS NULL").select("tree_id", F.col("node_id").alias("ptr"), F.lit(True).alias("is_root"))
    return ptr.groupBy("tree_id", "ptr").agg(F.count(F.lit(1)).alias("n_vertices")).join(roots, ["tree_id", "ptr"], "left").select("tree_id", F.col("ptr").alias("comp_id"), "n_vertices", F.coalesce("is_root", F.lit(False)).alias("is_root"))


def naive_partition(bt: DataFrame, m: int, kind: str = "hash") -> DataFrame:
    """(edges, cut_edges) when vertices are dealt to m machines by hash or by id range."""
    if kind == "hash":
        place = lambda c: F.pmod(F.xxhash64(c), F.lit(m))
    else:
        span = bt.agg(F.min("node_id"), F.max("node_id")).first()
        width = max(1, (span[1] - span[0]) // m + 1)
        place = lambda c: F.floor((c - span[0]) / width)
    edges = bt.where("parent_id IS NOT NULL")
    return edges.agg(F.count(F.lit(1)).alias("edges"), F.sum((place(F.col("node_id")) != place(F.col("parent_id"))).cast("long")).alias("cut_edges"))


def exhaustive_small(parent: list[int], edge_w: list[int], node_w: list[int], problem: str) -> int:
    """Exact answers of small trees by trying every subset; for tests."""
    n = len(parent)
    edges = [(v, parent[v], edge_w[v]) for v in range(n) if parent[v] >= 0]
    best = None
    if problem in ("mwm", "mcm"):
        for r in range(1 << len(edges)):
            chosen = [e for i, e in enumerate(edges) if r >> i & 1]
            ends = [x for v, u, _ in chosen for x in (v, u)]
            if len(ends) == len(set(ends)):
                w = len(chosen) if problem == "mcm" else sum(e[2] for e in chosen)
                best = w if best is None else max(best, w)
        return best
    if problem == "mec":
        for r in range(1 << len(edges)):
            chosen = [e for i, e in enumerate(edges) if r >> i & 1]
            if {x for v, u, _ in chosen for x in (v, u)} == set(range(n)):
                w = sum(e[2] for e in chosen)
                best = w if best is None else min(best, w)
        return best
    if problem == "lpath":
        near = {v: [] for v in range(n)}
        for v, u, w in edges:
            near[v].append((u, w))
            near[u].append((v, w))
        best = 0
        for s in range(n):
            stack = [(s, -1, 0)]
            while stack:
                x, p, d = stack.pop()
                best = max(best, d)
                stack += [(y, x, d + w) for y, w in near[x] if y != p]
        return best
    near = {v: {v} for v in range(n)}
    for v, u, _ in edges:
        near[v].add(u)
        near[u].add(v)
    for size in range(n + 1):
        for chosen in itertools.combinations(range(n), size):
            c = set(chosen)
            inside = any(v in c and u in c for v, u, _ in edges)
            covers = all(v in c or u in c for v, u, _ in edges)
            dominates = all(near[v] & c for v in range(n))
            w = sum(node_w[v] for v in c)
            ok = {"mis": not inside, "mvc": covers, "mds": dominates, "mids": dominates and not inside}[problem]
            if ok:
                best = w if best is None else (max(best, w) if problem == "mis" else min(best, w))
    return best


def weighted_intervals(rows: DataFrame, group: str, start: str, end: str, weight: str) -> DataFrame:
    """(group, value): heaviest set of disjoint intervals [start, end) of each group, one group in a task."""

    def run(table: pa.Table) -> pa.Table:
        from bisect import bisect_right

        items = sorted(zip(table[end].to_pylist(), table[start].to_pylist(), table[weight].to_pylist()))
        ends, best = [], [0]
        for e, s, w in items:
            best.append(max(best[-1], best[bisect_right(ends, s)] + w))
            ends.append(e)
        return pa.table({group: table[group].slice(0, 1), "value": pa.array([best[-1]], pa.int64())})

    return rows.select(group, start, end, weight).groupBy(group).applyInArrow(run, f"{group} long, value long")


def longest_increasing(rows: DataFrame, group: str, order: str, value: str) -> DataFrame:
    """(group, length): longest strictly increasing subsequence of each group."""

    def run(table: pa.Table) -> pa.Table:
        from bisect import bisect_left

        tails: list = []
        for _, v in sorted(zip(table[order].to_pylist(), table[value].to_pylist())):
            at = bisect_left(tails, v)
            tails[at : at + 1] = [v]
        return pa.table({group: table[group].slice(0, 1), "length": pa.array([len(tails)], pa.int64())})

    return rows.select(group, order, value).groupBy(group).applyInArrow(run, f"{group} long, length long")


def grouped_levels(tree: DataFrame) -> DataFrame:
    """(tree_id, depth, vertices): how many rounds a level-by-level method needs, and their sizes."""
    with_depth, _ = depths(tree)
    return with_depth.groupBy("tree_id", "depth").agg(F.count(F.lit(1)).alias("vertices"))


