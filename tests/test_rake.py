"""Subtree sizes by taking leaves off in turns, and the bisection that comes from them without a decomposition."""

import numpy as np
import pytest
from helpers import frame, values
from treefold.operators import bottom_up, linear
from treefold.plans import decompose, rake


def _bushy(n, seed):
    rng = np.random.default_rng(seed)
    up = [-1, *[int(rng.integers(0, v)) for v in range(1, n)]]
    return up, [0, *rng.integers(0, 40, n - 1).tolist()], [1] * n


@pytest.fixture
def small_space(monkeypatch):
    monkeypatch.setattr(decompose, "LOCAL_FLOOR", 40)
    monkeypatch.setattr(decompose, "LOCAL_FACTOR", 0.0)


def test_sizes_and_closest_chosen_vertices(spark, small_space):
    n = 500
    up, w, _ = tree = _bushy(n, 3)
    raked = rake.rake(frame(spark, {0: tree}), n, 4)
    assert len(raked.turns) > 1
    size = [1] * n
    for v in range(n - 1, 0, -1):
        size[up[v]] += size[v]
    ranked = sorted(range(1, n), key=lambda v: (-(size[v] / w[v] if w[v] else np.inf), w[v], v))
    got = rake.largest(raked, 60)
    assert got == [(v, w[v], size[v], up[v]) for v in ranked[:60]]
    want = {}
    for v in ranked[:60]:
        p = up[v]
        while p and p not in ranked[:60]:
            p = up[p]
        want[v] = p
    assert rake.closest(raked, {v: p for v, _, _, p in got}) == want


def test_long_paths_and_rows_that_are_no_tree_are_left_alone(spark, small_space):
    n = 200
    path = [-1, *range(n - 1)]
    assert rake.rake(frame(spark, {0: (path, [1] * n, [1] * n)}), n, 4) is None
    loose = _bushy(n, 1)
    loose[0][150] = 999
    assert rake.rake(frame(spark, {0: loose}), n, 4) is None


@pytest.mark.parametrize("most_kids", [2, 3])
def test_a_complete_tree_is_bisected_without_a_decomposition(spark, small_space, monkeypatch, most_kids):
    for name, value in (("LIGHT_FROM", 100), ("CUT_EDGES", 60), ("FIRST_EDGES", 16)):
        monkeypatch.setattr(linear, name, value)
    n, rng = 401, np.random.default_rng(7)
    w = rng.integers(1, 20, n).tolist()
    for v in (150, 260, 390):
        w[v] = 0
    df = frame(spark, {0: ([-1, *[(v - 1) // most_kids for v in range(1, n)]], w, [1] * n)})
    want = values(bottom_up.bisection_sequential(df))
    monkeypatch.setattr(linear, "prepare_tree", lambda *a, **k: pytest.fail("decomposed"))
    assert values(linear.bisection(df, 4, local_elements=0)) == want
