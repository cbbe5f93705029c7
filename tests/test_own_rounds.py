"""A report on a decomposition makes its own."""

import os

from treefold import queries
from treefold.plans.iterate import shared_dir


def test_rounds_read_the_table(spark, sf):
    # a tree made by an earlier query is not what this one reports
    queries.ready(spark, sf, "random")
    before = set(os.listdir(shared_dir(spark).removeprefix("file:")))
    assert queries.queries()["dec_rounds_random"](spark, sf).count()
    assert set(os.listdir(shared_dir(spark).removeprefix("file:"))) - before
