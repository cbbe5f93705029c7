"""Queries over whole tables, where the registered small cases read a prefix."""

import numpy as np
import pyarrow.parquet as pq

from helpers import frame
from treefold import queries
from treefold.operators.bottom_up import k_center, k_partition


def _weights(sf):
    t = pq.read_table(f"{sf}/events.parquet", columns=["event_id", "value"]).sort_by("event_id")
    return np.rint(t["value"].to_numpy() * 100).astype(np.int64)


def _one(df):
    (row,) = df.collect()
    return row["value"]


def test_spanning_chain_of_all_events(spark, sf):
    w = _weights(sf)
    sums = np.concatenate([[0], np.cumsum(w[1:])])
    for k in (2, 1000):
        every = sums[k - 1 :] - sums[: len(w) - k + 1]
        assert _one(queries.queries()[f"kmin_chain_all_k{k}"](spark, sf)) == every.min()
        assert _one(queries.queries()[f"kmax_chain_all_k{k}"](spark, sf)) == every.max()


def test_bisection_of_all_events(spark, sf):
    w, big = _weights(sf), 1 << 60
    # cost by (label of the last vertex, number labelled 1), vertex after vertex
    a, b = np.full(len(w) + 1, big), np.full(len(w) + 1, big)
    a[0] = b[1] = 0
    for x in w[1:].tolist():
        a, b = np.minimum(a, b + x), np.concatenate([[big], np.minimum(b, a + x)[:-1]])
    want = min(a[len(w) // 2], b[len(w) // 2])
    for name in ("bisect_chain_all", "bisect_grid_chain_all", "bisect_sequential_chain_all"):
        assert _one(queries.queries()[name](spark, sf)) == want, name
    heap = [_one(queries.queries()[name](spark, sf)) for name in ("bisect_heap", "bisect_sequential_heap")]
    assert heap[0] == heap[1] is not None


def test_trees_above_the_old_bound(spark):
    n = 6001
    path = frame(spark, {0: ([-1, *range(n - 1)], [0] + [2] * (n - 1), [1] * n)})
    assert _one(k_center(path, 1)) == n - 1
    assert _one(k_partition(path, 10)) == -(-n // 10)
