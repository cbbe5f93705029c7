"""The labelled sample beside a text that does not fit."""

from treefold.llm.common import labelled_sample


def test_a_long_text_does_not_end_the_sample(spark):
    rows = [(i, f"text number {i:02d}") for i in range(40)]
    marks = spark.createDataFrame([(i, i % 2) for i in range(40)], "doc_id long, toxic int")
    whole = labelled_sample(spark.createDataFrame(rows, "doc_id long, text string"), marks, "toxic", 5, 0, 100, 10_000)
    first = whole[0][0]
    rows[first] = (first, "x" * 20_000)
    got = labelled_sample(spark.createDataFrame(rows, "doc_id long, text string"), marks, "toxic", 5, 0, 100, 10_000)
    assert got == whole[1:] and {y for *_, y in got} == {0, 1}
