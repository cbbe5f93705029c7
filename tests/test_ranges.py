"""Turns inside ranges of ids before the turns over the whole tree."""

import numpy as np
import pytest
from helpers import frame, random_trees
from treefold import measures
from treefold.operators import finite, linear
from treefold.plans import decompose
from treefold.sources.generator import generate


@pytest.fixture
def small_ranges(monkeypatch):
    made = []
    inside = decompose.within_ranges
    for name, value in (("RANGES_FROM", 100), ("RANGE_ROWS", 150), ("NEAR", 64), ("LOCAL_FLOOR", 20), ("LOCAL_FACTOR", 0.0)):
        monkeypatch.setattr(decompose, name, value)
    monkeypatch.setattr(decompose, "within_ranges", lambda *a: made.append(inside(*a)) or made[-1])
    return made


@pytest.mark.parametrize("kind,near", [("chain", True), ("caterpillar", True), ("heap", False)])
def test_pieces_keep_their_bounds(spark, small_ranges, kind, near):
    n = 1023
    ready = finite.prepare_tree(generate(spark, kind, n), 4, seed=1)
    assert [got is not None for got in small_ranges] == [near]
    assert all(measures.check_decomposition(ready.bt, ready.dec).values())
    assert measures.leaf_identity(ready.dec.comp, "comp_id", "parent_comp") == 0
    if near:
        # most of the work is done by then
        assert small_ranges[0][2]["alive"] < n // 4


def test_forests_and_spans_over_ranges(spark, small_ranges):
    rng = np.random.default_rng(0)
    long = {9: ([-1, *[max(0, i - int(rng.integers(1, 4))) for i in range(1, 500)]], rng.integers(1, 50, 500).tolist(), [1] * 500)}
    df = frame(spark, random_trees(6, 60, 2) | long).cache()
    ready = finite.prepare_tree(df, 4)
    assert small_ranges and all(got is not None for got in small_ranges)
    assert all(measures.check_decomposition(ready.bt, ready.dec).values())
    for problem in (linear.K_MIN, linear.K_MAX):
        got = sorted(tuple(r) for r in linear.solve_vectors(ready, problem, most=6).collect())
        assert got == sorted(tuple(r) for r in linear.solve_vectors(finite.prepare_tree(df, 4, local_rows=10**6), problem, most=6).collect())
    assert len(small_ranges) == 1


def test_a_binary_tree_is_not_made_binary_again(spark, monkeypatch):
    monkeypatch.setattr(finite, "binary_extension", lambda *a: pytest.fail("children were collected"))
    df = generate(spark, "caterpillar", 101)
    bt = finite.prepare_tree(df, 4).bt
    assert all(measures.check_binary_extension(df, bt).values())
