"""Shares and families stay bounded when the tables grow."""

from helpers import frame
from treefold.operators import finite
from treefold.operators.binarize import MOST_CHILDREN, default_cap


def test_cap_fits_a_row():
    assert default_cap(1000, 8) == 125
    assert default_cap(42_000_000, 8) == MOST_CHILDREN


def test_shares_fit_a_task(spark, monkeypatch):
    monkeypatch.setattr(finite, "MOST_SHARE", 20)
    trees = {0: ([-1, *range(59)], [1] * 60, [1] * 60)}
    ready = finite.prepare_tree(frame(spark, trees), 1)
    assert ready.dec.m == 3
