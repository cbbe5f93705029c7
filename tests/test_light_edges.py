"""Bisection of a large tree over its lightest edges."""

import numpy as np
import pytest
from helpers import frame, random_trees, values
from treefold.operators import bottom_up, linear


def _slow(a, b, size):
    out = [linear.INF] * size
    for i, x in enumerate(a.tolist()):
        for j, y in enumerate(b.tolist()):
            if i + j < size and max(x, y) < linear.INF:
                out[i + j] = min(out[i + j], x + y)
    return out


def test_convolution_by_values(monkeypatch):
    rng = np.random.default_rng(0)
    monkeypatch.setattr(linear, "DENSE", 3)
    for most in (None, 40, 70):
        for spread in (2, 7, 100):
            a, b = (np.where(rng.random(n) < 0.3, linear.INF, rng.integers(0, spread, n)) for n in (50, 33))
            size = 82 if most is None else min(82, most)
            assert linear.convolve(a, b, most).tolist() == _slow(a, b, size)
    assert linear.convolve(np.array([linear.INF, linear.INF]), np.array([0, 1])).tolist() == [linear.INF] * 3


def test_light_edges_give_the_same_bisection(spark, monkeypatch):
    asked = []
    whole = linear.solve_vectors
    monkeypatch.setattr(linear, "LIGHT_FROM", 10)
    monkeypatch.setattr(linear, "LIGHT_EDGES", (6, 20))
    monkeypatch.setattr(linear, "solve_vectors", lambda *a, sized=False, **k: asked.append(sized) or whole(*a, sized=sized, **k))
    rng = np.random.default_rng(5)
    trees = [(([-1, *range(n - 1)], [0, *rng.integers(0, 30, n - 1).tolist()], [1] * n)) for n in (41, 60)]
    trees += [t for t in random_trees(30, 60, 9).values() if len(t[0]) > 30][:3]
    for t in trees:
        df = frame(spark, {4: t})
        want = values(bottom_up.bisection_sequential(df))
        for options in ({}, {"local_elements": 0}):
            assert values(linear.bisection(df, 4, **options)) == want
    assert True in asked


@pytest.mark.parametrize("n", [600])
def test_a_cheap_cut_is_proved_without_whole_vectors(spark, monkeypatch, n):
    monkeypatch.setattr(linear, "LIGHT_FROM", 100)
    monkeypatch.setattr(linear, "LIGHT_EDGES", (2, 4))
    monkeypatch.setattr(linear, "local_vectors", lambda ready, *a, f=linear.local_vectors, **k: f(ready, *a, **k) if ready.dec.n < 10 else pytest.fail("whole vectors"))
    w = [0] + [50] * (n - 1)
    w[100], w[400] = 3, 4
    assert values(linear.bisection(frame(spark, {0: ([-1, *range(n - 1)], w, [1] * n)}), 4)) == {0: 7}
