"""The sequential baseline with large trees in a file."""

import numpy as np
import pyarrow as pa
import pytest
from helpers import frame, random_trees, values
from treefold.operators import baselines, finite
from treefold.operators.problems import PROBLEMS


@pytest.mark.parametrize("problem", ["mis", "mds", "mwm", "lpath"])
def test_large_trees_in_a_file(spark, monkeypatch, problem):
    trees = random_trees(12, 60, 3)
    trees[20] = ([-1] + [0] * 70, list(range(71)), list(range(71)))
    df = frame(spark, trees).coalesce(1)
    whole = values(baselines.sequential(df, PROBLEMS[problem]()))
    made = df.sort("tree_id", "parent_id").toArrow()
    seen = []
    for table, stream in baselines.tree_runs(iter(made.to_batches(max_chunksize=7)), 5, 25):
        if stream is not None:
            rows = list(stream)
            monkeypatch.setattr(baselines, "CHUNK_ROWS", 9)
            (value,) = baselines.fold_stream(finite.Tables(PROBLEMS[problem]()), iter(rows))
            tree = rows[0].column("tree_id")[0].as_py()
            assert value == whole[tree] and {t for b in rows for t in b.column("tree_id").to_pylist()} == {tree}
            seen += [tree] * sum(b.num_rows for b in rows)
        else:
            seen += table["tree_id"].to_pylist()
    assert seen == made["tree_id"].to_pylist()
    assert any(len(t[0]) > 25 for t in trees.values())


def test_memory_of_a_large_tree():
    """A tree whose vertices are mostly leaves is not held whole."""
    import tracemalloc

    n, inner = 2_000_000, 50_000
    above = np.r_[-1, np.zeros(inner - 1, np.int64), np.sort(np.arange(n - inner) % (inner - 1) + 1)]

    def rows():
        for a in range(0, n, 10_000):
            node = np.arange(a, min(n, a + 10_000))
            yield pa.RecordBatch.from_arrays([pa.array(np.zeros(len(node), np.int64)), pa.array(node), pa.array(above[node], mask=above[node] < 0), pa.array(node % 7), pa.array(node % 5)], ["tree_id", "node_id", "parent_id", "node_w", "edge_w"])

    tracemalloc.start()
    (value,) = baselines.fold_stream(finite.Tables(PROBLEMS["mis"]()), rows())
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert value == sum(i % 7 for i in range(inner, n)) and peak < n * 8 * 9
