"""Vectors that end at the number asked for, and the array form of the sequential baseline."""

import time

import numpy as np
import pytest
from helpers import frame, random_trees
from treefold.operators import bottom_up, finite, linear


@pytest.mark.parametrize("problem", [linear.BISECTION, linear.K_MIN, linear.K_MAX])
def test_vectors_end_at_most(spark, problem):
    df = frame(spark, random_trees(10, 12, 7)).cache()
    ready = finite.prepare_tree(df, m=100, seed=3)
    for options in ({"finish": "master"}, {"finish": "grid", "local_elements": 0, "block": 2}):
        whole = sorted(tuple(r) for r in linear.solve_vectors(ready, problem, **options).where("idx <= 3").collect())
        assert sorted(tuple(r) for r in linear.solve_vectors(ready, problem, most=3, **options).collect()) == whole


def test_least_span_of_a_large_heap():
    n, k = 60_000, 5
    parent, w = (np.arange(n) + 1) // 2 - 1, np.random.default_rng(0).integers(1, 100, n)
    table = linear.fold_piece(linear.K_MIN, list(range(n)), {i: int(parent[i]) for i in range(1, n)}, dict.fromkeys(range(n), False), dict(enumerate(w.tolist())), {}, k)
    assert bottom_up.least_span(parent, w, k) == min(v[k] for v in table.table.values())


def _whole(trees):
    """All trees as rows sorted by (tree, vertex), a helper here and there."""
    rng = np.random.default_rng(1)
    out = []
    for t, (parent, edge, _) in trees.items():
        kids = np.bincount([p for p in parent if p >= 0], minlength=len(parent))
        if kids.max(initial=0) > 2:
            continue
        aux = (kids == 2) & (rng.random(len(parent)) < 0.5)
        aux[0] = False
        out.append((parent, np.where(aux, 0, edge), aux))
    return out


@pytest.mark.parametrize("problem", [linear.K_MIN, linear.K_MAX])
@pytest.mark.parametrize("most", [0, 1, 2, 5, 40])
def test_spans_on_arrays_are_those_of_single_vertices(problem, most):
    rng = np.random.default_rng(most)
    checked = 0
    for parent, edge, aux in _whole(random_trees(400, 30, 11)):
        n = len(parent)
        # pieces are whole trees here; up to three ends of cut edges
        border = np.unique(rng.integers(0, n, rng.integers(0, 4)))
        want = linear.fold_piece(problem, list(range(n)), {v: p for v, p in enumerate(parent) if p >= 0}, dict(enumerate(aux.tolist())), dict(enumerate(edge.tolist())), dict.fromkeys(border.tolist(), 1), most)
        (got,) = linear.span_pieces(problem, np.zeros(n, int), np.arange(n), np.array(parent), aux, edge, border, most)
        assert sorted(got.border) == sorted(want.border)
        full = lambda t: {(linear.project(c, t.border, sorted(t.border)), i): x for c, v in t.table.items() for i, x in enumerate(v.tolist()) if x < linear.INF // 2}
        assert full(got) == full(want), (parent, border)
        checked += 1
    assert checked > 50


def test_spans_of_a_long_path_take_arrays():
    """200,000 vertices and k = 1000: vertex by vertex this took 16 s."""
    n, k = 200_000, 1000
    w = np.random.default_rng(0).integers(1, 10_000, n)
    began = time.process_time()
    (got,) = linear.span_pieces(linear.K_MAX, np.zeros(n, int), np.arange(n), np.arange(n) - 1, np.zeros(n, bool), w, np.array([0, n - 1]), k)
    assert time.process_time() - began < 8
    sums = np.cumsum(w)
    spans = sums[k - 1 :] - sums[: n - k + 1]
    # a set that holds neither end
    assert -got.table[0][k] == spans[1:-1].max() and -got.table[1][k] == spans[0] and -got.table[2][k] == spans[-1] and got.table.get(3, [linear.INF] * (k + 1))[k] >= linear.INF // 2
