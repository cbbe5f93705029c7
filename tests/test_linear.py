import math
import random

import pytest
from helpers import ANSWERS, HAND, brute_location, brute_parts, frame, hand_frame, profile, random_trees, values
from treefold.operators import bottom_up, linear
from treefold.operators.finite import prepare_tree
from treefold.plans import schedule
from treefold.plans.decompose import Rules


@pytest.fixture(scope="module")
def small(spark):
    trees = random_trees(20, 8, 5)
    df = frame(spark, trees).cache()
    return trees, df, prepare_tree(df, m=300, shape="comb", seed=3, cap=3)


@pytest.mark.parametrize("problem,kind,sign", [(linear.BISECTION, "cut", 1), (linear.K_MIN, "span", 1), (linear.K_MAX, "span", -1)])
def test_profiles(small, problem, kind, sign):
    trees, _, ready = small
    for options in ({"finish": "master"}, {"finish": "grid", "local_elements": 0, "block": 2}):
        got = {}
        for r in linear.solve_vectors(ready, problem, **options).collect():
            got.setdefault(r["tree_id"], {})[r["idx"]] = r["value"]
        assert got == {t: profile(x, kind, sign) for t, x in trees.items()}, options


def test_finishes_agree(spark):
    from treefold.sources import generate

    df = generate(spark, "random", 60)
    ready = prepare_tree(df, m=3, rules=Rules(stop_factor=2))
    found = [sorted(map(tuple, linear.solve_vectors(ready, linear.BISECTION, finish=f, block=7, local_elements=0).collect())) for f in linear.FINISHES]
    assert all(x == found[0] for x in found) and len(found[0]) == 61
    best = {i: v for _, i, v in found[0]}
    assert all(best[i] == best[60 - i] for i in range(61))  # colours may be swapped


def test_hand_trees(spark):
    df = hand_frame(spark)
    want = lambda key: {i: ANSWERS[h][key] for i, h in enumerate(HAND)}
    ready = prepare_tree(df, m=2)
    profile_ = linear.solve_vectors(ready, linear.BISECTION)
    assert values(linear.answer_at(profile_, df, linear.BISECTION)) == want("bisection") == values(bottom_up.bisection_sequential(df))
    for sense, key, problem in (("min", "kmin", linear.K_MIN), ("max", "kmax", linear.K_MAX)):
        assert values(linear.answer_at(linear.solve_vectors(ready, problem), df, problem, 3)) == want(key) == values(bottom_up.k_spanning_sequential(df, 3, sense))
    assert values(bottom_up.k_center(df, 2)) == want("kcenter")
    assert values(bottom_up.k_median(df, 2)) == want("kmedian")
    assert values(bottom_up.facility_location(df)) == want("ufl")


def test_infeasible(spark):
    df = frame(spark, {0: HAND["path3"]})
    row = linear.k_spanning(df, 9, m=1).first()
    assert row["value"] is None and not row["feasible"]
    assert linear.k_spanning(df, 3, m=1).first()["value"] == 6


def test_location_problems(small):
    trees, df, _ = small
    for name, call, k in (("ufl", bottom_up.facility_location(df), 0), ("kcenter", bottom_up.k_center(df, 2), 2), ("kmedian", bottom_up.k_median(df, 2), 2), ("mindiam", bottom_up.minimum_diameter(df, 3), 3)):
        assert values(call) == {t: brute_location(x, name, k) for t, x in trees.items()}, name
    assert values(bottom_up.k_partition(df, 3)) == {t: brute_parts(x, 3) for t, x in trees.items()}


def test_schedule_bounds():
    rng = random.Random(2)
    for t in range(80):
        n = rng.randint(1, 150)
        parents, open_ = {0: None}, [0, 0]
        for i in range(1, n):
            p = open_.pop(rng.randrange(len(open_)) if t % 2 else len(open_) - 1)
            parents[i] = p
            open_ += [i, i]
        plan = schedule.build_plan(parents)
        assert sorted(c[2] for c in plan) == list(range(1, n))
        parts = {v: {v} for v in parents}
        border = lambda nodes: sum(1 for v, p in parents.items() if p is not None and (v in nodes) != (p in nodes))  # noqa: E731,B023
        for _, half, _, left, right, out in plan:
            a, b = parts.pop(left), parts.pop(right)
            assert max(border(a), border(b)) <= 4
            parts[out] = a | b
            assert border(a | b) <= (3 if half == 2 else 4)
        assert len(parts) == 1
        assert max([0, *(c[0] for c in plan)]) <= math.log(n, 1.5) + 2


def test_convolution_expression(spark):
    from pyspark.sql import functions as F

    from treefold.functions.columns import max_plus, min_plus_convolution

    df = spark.createDataFrame([([1, 5, 2], [0, 3])], "a array<bigint>, b array<bigint>")
    import numpy as np

    assert df.select(min_plus_convolution(F.col("a"), F.col("b"))).first()[0] == linear.convolve(np.array([1, 5, 2]), np.array([0, 3])).tolist()
    assert df.select(max_plus(F.col("a"), F.col("a"))).first()[0] == 10
