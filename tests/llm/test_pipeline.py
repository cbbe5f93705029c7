"""The corpus pipeline, stage by stage."""

import numpy as np


def test_stages(spark, sf):
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    counts = [docs.count()]
    for name, stage in cp.STAGES[:-1]:
        after = cp.materialise(stage(spark, docs, sf), name)
        assert after.columns == columns and dict(after.dtypes) == dict(docs.dtypes), name
        if name != "mixing":
            assert after.select("doc_id").exceptAll(docs.select("doc_id")).count() == 0
        if name == "quality_classifier":
            marks = spark.read.parquet(f"{sf}/labels.parquet").where("quality = 1").join(docs, "doc_id")
            kept = marks.join(after, "doc_id", "left_semi").count()
            assert kept >= 0.9 * marks.count()
        docs = after
        counts.append(docs.count())
    assert counts[0] > counts[1] >= counts[2] >= counts[3] > 0
    packed = cp.STAGES[-1][1](spark, docs, sf).toPandas()
    assert np.all(packed.groupby("sequence_id").length.sum() <= 2048)
    assert set(packed.doc_id) == {r["doc_id"] for r in docs.select("doc_id").distinct().collect()}


def test_run_equals_its_stages(spark, sf):
    import corpus_pipeline as cp

    out = cp.run(spark, sf)
    assert out.columns == ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
    assert out.count() > 0


def test_empty(spark, sf):
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(0)
    for _, stage in cp.STAGES:
        assert stage(spark, docs, sf).count() == 0
