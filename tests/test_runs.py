"""Bisection over the edges that move many vertices for their weight, on runs of equal cost."""

import numpy as np
import pytest
from helpers import frame, values
from treefold.operators import bottom_up, linear, runs


def test_runs_of_the_least_cost():
    rng = np.random.default_rng(0)
    for _ in range(200):
        k = int(rng.integers(1, 12))
        lo, cost = rng.integers(0, 30, k), rng.integers(0, 5, k)
        hi = lo + rng.integers(0, 8, k)
        want, got = np.full(60, 99), np.full(60, 99)
        for a, b, c in zip(lo, hi, cost):
            want[a : b + 1] = np.minimum(want[a : b + 1], c)
        made = runs.least(lo, hi, cost)
        assert (made[0][1:] > made[1][:-1]).all()
        for a, b, c in zip(*made):
            got[a : b + 1] = c
        assert got.tolist() == want.tolist()


def test_a_complete_tree_is_bisected_without_whole_vectors(spark, monkeypatch):
    monkeypatch.setattr(linear, "LIGHT_FROM", 100)
    monkeypatch.setattr(linear, "LIGHT_EDGES", (4, 8))
    monkeypatch.setattr(linear, "CUT_EDGES", 40)
    monkeypatch.setattr(linear, "FIRST_EDGES", 16)
    n, rng = 401, np.random.default_rng(7)
    w = rng.integers(5, 60, n).tolist()
    for v in (150, 260, 390):
        w[v] = 0
    df = frame(spark, {0: ([-1, *[(v + 1) // 2 - 1 for v in range(1, n)]], w, [1] * n)})
    want = values(bottom_up.bisection_sequential(df))
    monkeypatch.setattr(linear, "local_vectors", lambda *a, **k: pytest.fail("whole vectors"))
    assert values(linear.bisection(df, 4, local_elements=0)) == want


def _small(rng, n, reach):
    up = {v: int(rng.integers(max(0, v - reach), v)) for v in range(1, n)}
    return up, {v: int(rng.integers(0, 5)) for v in range(n)}, {v: int(rng.integers(0, 9)) for v in range(1, n)}


def test_pieces_of_a_small_tree_are_few_and_touch_three_cut_edges_at_most():
    rng = np.random.default_rng(3)
    for reach in (1, 2, 400):
        up, size, _ = _small(rng, 400, reach)
        _, par = linear._binary(up, size)
        assert np.bincount(par[par >= 0]).max() <= 2
        top, merges = linear._runs_plan(par, 6, 12)
        pieces = np.unique(top)
        assert len(pieces) <= 12 and len(merges) == len(pieces) - 1
        # one turn of jobs for each, not for each halving of single vertices
        assert len({x[:2] for x in merges}) <= 8
        ends = np.bincount(np.searchsorted(pieces, [top[v] for _, _, child, above, _, _ in merges for v in (child, above)]), minlength=len(pieces))
        assert ends.max() <= 3


@pytest.mark.parametrize("reach", [1, 60])
def test_merged_pieces_give_the_profile_of_the_sequential_form(spark, reach):
    up, size, weight = _small(np.random.default_rng(reach), 60, reach)
    n = sum(size.values())
    most, cap = n // 2 + 3, 25
    want = runs.fold(up, size, weight, most, cap)
    got = linear.solve_runs(spark, 0, up, size, weight, 4, n, most, cap, parts=7)
    assert [runs.at(got, k) for k in range(most + 1)] == [runs.at(want, k) for k in range(most + 1)]
    dense = bottom_up.bisection_sequential(frame(spark, {0: ([up.get(v, -1) for v in range(60)], [weight.get(v, 0) for v in range(60)], [1] * 60)}))
    ones = dict.fromkeys(range(60), 1)
    assert values(dense) == {0: runs.at(linear.solve_runs(spark, 0, up, ones, weight, 4, 60, 30, 1000, parts=7), 30)}


def test_runs_of_very_different_lengths():
    rng = np.random.default_rng(2)
    lo, cost = rng.integers(0, 5000, 400), rng.integers(0, 30, 400)
    hi = lo + rng.integers(0, 1 << 12, 400) // rng.integers(1, 4000, 400)
    want = np.full(10000, 99)
    for a, b, c in zip(lo, hi, cost):
        want[a : b + 1] = np.minimum(want[a : b + 1], c)
    made = runs.least(lo, hi, cost)
    got = np.full(10000, 99)
    for a, b, c in zip(*made):
        got[a : b + 1] = c
    assert got.tolist() == want.tolist()
    # neighbours of one cost are one run
    assert not ((made[0][1:] == made[1][:-1] + 1) & (made[2][1:] == made[2][:-1])).any()
