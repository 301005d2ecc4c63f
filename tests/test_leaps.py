"""Edges that a leap outlasts."""

import numpy as np

from ivsearch.operators import kernels


def test_places_that_end_within_a_leap_go_to_others():
    v = np.concatenate([np.diag([1.0, 1.1, 1.2, 1.3]), np.zeros((1, 4))])  # no object is nearer to another than to the last one
    xr, ids = np.array([1, 4, 5, 6, 6]), np.arange(4)
    edges, rounds, gap = kernels.sweep_pooled(v, xr, 4, ids, kernels.dist2(v, ids, v[4]), 2, "max")
    assert sorted(edges) == [(0, 0, 1), (1, 0, 4), (2, 2, 5), (3, 5, 6)] and rounds == 2 and gap is None
