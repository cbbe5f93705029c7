"""Small trees and brute force for the tests."""

import itertools
import random
from collections import Counter

from treefold.model import TREE

# parent lists with the root first; edge and vertex weights by vertex
HAND = {
    "path3": ([-1, 0, 1], [0, 1, 5], [3, 4, 2]),
    "two_children": ([-1, 0, 0], [0, 5, 4], [3, 4, 2]),
    "four_with_leaves": ([-1, 0, 0, 0, 0, 1, 2, 3, 4], [0, 1, 1, 1, 1, 10, 10, 10, 10], [1] * 9),
    "star": ([-1, 0, 0, 0, 0, 0], [0, 3, 1, 4, 1, 5], [7, 1, 1, 1, 1, 1]),
    "complete15": ([-1, *[(i - 1) // 2 for i in range(1, 15)]], list(range(15)), list(range(1, 16))),
    "path10": ([-1, *range(9)], [0, 3, 1, 4, 1, 5, 9, 2, 6, 5], [3, 1, 4, 1, 5, 9, 2, 6, 5, 3]),
}
ANSWERS = {
    "path3": dict(mwm=5, mis=5, mvc=4, mds=4, lpath=6, bisection=1, kmax=6, kmin=6, kcenter=1, kmedian=1, ufl=6, subtree_sum=9),
    "two_children": dict(mwm=5, mis=6, mvc=3, mds=3, lpath=9, bisection=4, kmax=9, kmin=9, kcenter=4, kmedian=4, ufl=9, subtree_sum=9),
    "four_with_leaves": dict(mwm=40, mis=5, mvc=4, mds=4, lpath=22, bisection=2, kmax=11, kmin=2, kcenter=11, kmedian=37, ufl=9, subtree_sum=9),
    "star": dict(mwm=5, mis=7, mvc=5, mds=5, lpath=9, bisection=5, kmax=9, kmin=2, kcenter=4, kmedian=9, ufl=6, subtree_sum=12),
    "complete15": dict(mwm=46, mis=97, mvc=23, mds=23, lpath=37, bisection=1, kmax=27, kmin=3, kcenter=17, kmedian=133, ufl=110, subtree_sum=120),
    "path10": dict(mwm=22, mis=25, mvc=14, mds=7, lpath=36, bisection=3, kmax=14, kmin=4, kcenter=8, kmedian=43, ufl=25, subtree_sum=39),
}


def rows_of(trees):
    out = []
    for t, (parent, edge, node) in trees.items():
        for v, p in enumerate(parent):
            out.append((t, v, p if p >= 0 else None, 0, node[v], edge[v] if p >= 0 else None))
    return out


def frame(spark, trees):
    return spark.createDataFrame(rows_of(trees), TREE)


def hand_frame(spark):
    return frame(spark, dict(enumerate(HAND.values())))


def random_trees(count, most, seed, low=0):
    rng = random.Random(seed)
    trees = {}
    for t in range(count):
        n = rng.randint(1, most)
        reach = rng.choice([1, 2, 50])
        parent = [-1, *[rng.randrange(max(0, i - reach), i) for i in range(1, n)]]
        trees[t] = (parent, [rng.randint(0, 9) for _ in range(n)], [rng.randint(low, 9) for _ in range(n)])
    return trees


def values(df):
    return {r["tree_id"]: r["value"] for r in df.collect()}


def profile(tree, kind, sign=1):
    """Best cost for every number of marked vertices, over all subsets."""
    parent, edge, _ = tree
    n, out = len(parent), {}
    for bits in range(1 << n):
        s = {i for i in range(n) if bits >> i & 1}
        if kind == "cut":
            cost = sum(edge[v] for v in range(n) if parent[v] >= 0 and (v in s) != (parent[v] in s))
        else:
            if sum(parent[v] < 0 or parent[v] not in s for v in s) > 1:
                continue
            cost = sum(edge[v] for v in s if parent[v] >= 0 and parent[v] in s)
        k = len(s)
        if k not in out or sign * cost < sign * out[k]:
            out[k] = cost
    return out


def distance_matrix(parent, edge):
    n = len(parent)
    d = [[0 if i == j else 10**9 for j in range(n)] for i in range(n)]
    for v, p in enumerate(parent):
        if p >= 0:
            d[v][p] = d[p][v] = edge[v]
    for k, i, j in itertools.product(range(n), repeat=3):
        d[i][j] = min(d[i][j], d[i][k] + d[k][j])
    return d


def brute_location(tree, problem, k):
    parent, edge, node = tree
    n, d, best = len(parent), distance_matrix(parent, edge), None
    for bits in range(1, 1 << n):
        s = [i for i in range(n) if bits >> i & 1]
        near = [min(d[v][u] for u in s) for v in range(n)]
        if problem == "ufl":
            cost = sum(node[i] for i in s) + sum(near)
        elif problem in ("kcenter", "kmedian"):
            if len(s) > k:
                continue
            cost = max(near) if problem == "kcenter" else sum(near)
        else:  # least diameter of k connected vertices
            chosen = set(s)
            if len(s) != k or sum(parent[v] < 0 or parent[v] not in chosen for v in s) > 1:
                continue
            cost = max(d[a][b] for a in s for b in s)
        best = cost if best is None else min(best, cost)
    return best


def brute_parts(tree, cap):
    parent = tree[0]
    edges = [v for v in range(len(parent)) if parent[v] >= 0]
    for size in range(len(edges) + 1):
        for cut in itertools.combinations(edges, size):
            part = {}
            for v in range(len(parent)):
                part[v] = v if parent[v] < 0 or v in cut else part[parent[v]]
            if max(Counter(part.values()).values()) <= cap:
                return size + 1
    return None
