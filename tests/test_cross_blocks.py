"""Block numbers come from a table."""

from treefold import queries


def test_cross_blocks_come_from_events(spark, sf):
    got = queries.queries()["op_cross_blocks"](spark, sf)
    assert any("events.parquet" in f for f in got.inputFiles())
    assert sorted(map(tuple, got.collect())) == [(i, j) for i in range(6) for j in range(4)]
