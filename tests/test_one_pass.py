"""A large tree with near ids is not looked at again for what the turns inside ranges see anyway."""

import numpy as np
import pytest
from helpers import frame
from treefold import measures
from treefold.operators import bottom_up, finite, linear
from treefold.plans import decompose
from treefold.sources.generator import generate


@pytest.fixture
def short(monkeypatch):
    for name, value in (("RANGES_FROM", 100), ("RANGE_ROWS", 150), ("NEAR", 64), ("LOCAL_FLOOR", 20), ("LOCAL_FACTOR", 0.0)):
        monkeypatch.setattr(decompose, name, value)


def test_pieces_come_from_the_components_of_ranges(spark, short, monkeypatch):
    monkeypatch.setattr(decompose, "contracted_tree", lambda *a: pytest.fail("all vertices were read again"))
    ready = finite.prepare_tree(generate(spark, "caterpillar", 1023), 4, seed=1)
    monkeypatch.undo()
    assert all(measures.check_decomposition(ready.bt, ready.dec).values())
    columns = ready.dec.comp.columns
    want = decompose.contracted_tree(ready.bt, ready.dec.assign, ready.dec.n / 4)
    assert sorted(map(str, ready.dec.comp.collect())) == sorted(map(str, want.select(*columns).collect()))


def test_a_vertex_of_three_children_is_seen_inside_ranges(spark, short):
    # ids are near, and the third child of a vertex is in another range
    for n, odd in ((600, {260: 10, 262: 10}), (600, {300: 297, 301: 297, 302: 297})):
        parent = [-1, *range(n - 1)]
        for v, p in odd.items():
            parent[v] = p
        w = np.random.default_rng(n).integers(1, 50, n).tolist()
        df = frame(spark, {0: (parent, w, [1] * n)})
        ready = finite.prepare_tree(df, 4)
        assert all(measures.check_binary_extension(df, ready.bt).values())
        got = linear.k_spanning(df, 5, "min", 4).select("value").first()[0]
        assert got == bottom_up.k_spanning_sequential(df, 5).select("value").first()[0]


def test_ranges_by_cells(spark):
    rng = np.random.default_rng(3)
    for ids in (rng.integers(-(10**6), 10**12, 300), np.arange(40), np.r_[np.arange(200), 1 << 61]):
        for bounds in (sorted(set(rng.choice(ids, 5).tolist())), sorted(set(ids.tolist()))[1::2]):
            look = decompose.range_lookup(bounds, int(ids.min()), int(ids.max()))
            got = spark.createDataFrame([(int(v),) for v in ids], "v long").select("v", look("v").alias("r")).collect()
            assert [r["r"] for r in got] == np.searchsorted(bounds, [r["v"] for r in got], "right").tolist()
