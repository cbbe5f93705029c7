import numpy as np
from helpers import frame, random_trees
from pyspark.sql import functions as F

from treefold.functions import udfs
from treefold.operators import baselines
from treefold.operators.finite import merge
from treefold.plans.hashing import PolyHash


def test_table_functions(spark):
    udfs.register(spark)
    trees = random_trees(12, 9, 8)
    frame(spark, trees).createOrReplaceTempView("small_trees")
    got = {r["tree_id"]: r["value"] for r in spark.sql("SELECT * FROM tree_dp(TABLE(small_trees) PARTITION BY (tree_id), 'mis')").collect()}
    assert got == {t: baselines.exhaustive_small(*x, "mis") for t, x in trees.items()}
    spark.createDataFrame([(0, i, (i + 1) // 2 - 1 if i else None) for i in range(15)], "tree_id long, comp_id long, parent_comp long").createOrReplaceTempView("pieces")
    plan = spark.sql("SELECT * FROM split_plan(TABLE(pieces) PARTITION BY tree_id)").collect()
    assert sorted(r["child_comp"] for r in plan) == list(range(1, 15))
    rows = spark.sql("SELECT * FROM explode_path('https://a.b.org/en/page')").collect()
    assert [r["prefix"] for r in rows] == ["org", "org.b", "org.b.a", "org.b.a/en"]


def test_arrow_functions(spark):
    h = PolyHash(8, seed=2)
    rows = spark.range(100)
    assert rows.where(udfs.poly_hash_udf(h)("id") != h.column(F.col("id"))).count() == 0
    c, p = list(range(4)), list(range(8))
    df = spark.createDataFrame([(c, p)], "c array<long>, p array<long>")
    assert df.select(udfs.tensor_merge(2, 1)("c", "p")).first()[0] == merge(np.array(c), np.array(p), 1, 2).reshape(-1).tolist()
    kids = spark.createDataFrame([(1, [1, 2]), (1, [3, 4])], "k int, v array<long>")
    assert kids.groupBy("k").agg(udfs.fold_children("v", 2).alias("s")).first()["s"] == [4, 6]
