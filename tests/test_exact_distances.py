"""The matrix product only proposes pairs; distances and ties are those of the differences."""

import numpy as np
from treefold.plans import spanning


def test_least_of_rows_is_exact():
    x = np.random.default_rng(1).normal(size=(200, 64))
    x[50:80] = x[0]
    d, near = np.rint(((x[:, None] - x[None]) ** 2).sum(2) * spanning.SCALE), spanning.products(x, x)
    same = (np.arange(200) // 3)[:, None] == (np.arange(200) // 3)[None]
    d[same] = near[same] = np.inf
    at = np.arange(200)
    mine, other, w = spanning.least_of_rows(x, at, at, near)
    assert (mine == at).all() and (other == d.argmin(1)).all() and (w == d.min(1)).all()
