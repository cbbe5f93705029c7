"""Cost measures against plain counts."""

import math

import numpy as np

from helpers import frame, random_trees
from treefold import measures
from treefold.operators.finite import prepare_tree
from treefold.operators.linear import merge_edges
from treefold.plans import schedule
from treefold.plans.decompose import Rules
from treefold.plans.hashing import PolyHash
from treefold.sources import generate


def test_space_and_traffic(spark):
    n, m = 700, 9
    rows, h = generate(spark, "random", n), PolyHash(m, seed=2)
    parent = {r["node_id"]: r["parent_id"] for r in rows.collect()}
    place = dict(zip(parent, h.evaluate(np.array(list(parent))).tolist()))
    space = {r["machine"]: (r["rows"], r["bytes"]) for r in measures.machine_space(rows, h).collect()}
    assert space == {k: (c, 48 * c) for k in range(m) for c in [sum(v == k for v in place.values())]}
    sent, received = [0] * m, [0] * m
    for v, p in parent.items():
        if p is not None and place[v] != place[p]:
            sent[place[v]] += 1
            received[place[p]] += 1
    got = {r["machine"]: (r["sent"], r["received"]) for r in measures.machine_traffic(rows, h).collect()}
    assert got == {k: (sent[k], received[k]) for k in range(m) if sent[k] or received[k]}
    # every machine sends about its share, up to a log factor
    assert max(sent) <= n / m * math.log2(n)


def test_row_bytes(spark):
    df = spark.createDataFrame([(1, [1, 2, 3], "äb", None), (2, None, None, [])], "a long, b array<long>, c string, d array<long>")
    assert sorted(r[0] for r in df.select(measures.row_bytes(df)).collect()) == [8, 8 + 24 + 3]


def test_rounds_of_the_loop(spark):
    ready = prepare_tree(generate(spark, "random", 511), 2, local_rows=0)
    rounds = sorted(map(tuple, measures.decomposition_rounds(ready.dec).collect()))
    assert [r[0] for r in rounds] == list(range(ready.dec.iterations))
    assert all(a[1] > b[1] for a, b in zip(rounds, rounds[1:]))
    assert all(r[3] == 3 + math.ceil(math.log2(1 + r[2])) for r in rounds)


def test_merge_work(spark):
    trees = random_trees(6, 40, 3)
    ready = prepare_tree(frame(spark, trees), m=40, rules=Rules(stop_factor=2))
    plan = schedule.build(ready.dec.comp)
    work = measures.merge_work(ready, plan, 8).collect()
    assert len(work) == merge_edges(ready).count()
    last = {}
    for r in work:
        assert r["operations"] == r["left_n"] * r["right_n"]
        assert r["block_pairs"] == math.ceil(r["left_n"] / 8) * math.ceil(r["right_n"] / 8)
        last[r["tree_id"]] = max(last.get(r["tree_id"], 0), r["left_n"] + r["right_n"] - 2)
    # the last merge of a tree has all of its vertices, and the work is at most quadratic
    sizes = {t: len(parent) for t, (parent, *_) in trees.items()}
    assert all(last[t] == sizes[t] for t in last)
    for t in last:
        assert sum(r["operations"] for r in work if r["tree_id"] == t) <= 4 * sizes[t] ** 2


def test_hash_in_sql(spark):
    import duckdb

    h = PolyHash(16, seed=3)
    keys = [0, 1, 5, 12345, (1 << 31) - 2, 7_000_000_001, (1 << 60) + 17]
    df = spark.createDataFrame([(k,) for k in keys], "k long")
    wide = [r[0] for r in df.select(h.wide_column(df["k"])).collect()]
    narrow = [r[0] for r in df.select(h.column(df["k"])).collect()]
    con = duckdb.connect()
    for k, a, b in zip(keys, wide, narrow):
        assert con.sql(f"SELECT {h.sql('x', wide=True)}, {h.sql('x')} FROM (SELECT {k}::BIGINT AS x)").fetchall() == [(a, b)]
