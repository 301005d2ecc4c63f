"""The constructor that searches its own graph at every threshold."""

import numpy as np

from ivsearch.operators import kernels


def test_incremental_states_are_those_of_whole_sweeps_and_edges_are_written_once():
    rng = np.random.default_rng(8)
    n, m = 60, 4
    v, xr, yr = rng.normal(size=(n, 6)), np.unique(rng.integers(0, 30, n), return_inverse=True)[1], np.unique(np.sort(rng.integers(0, 30, n)), return_inverse=True)[1]
    rows, _, _ = kernels.build(v, np.arange(n), xr, yr, m, "incremental", n)
    for a in range(xr.max() + 1):
        for c in range(yr.max() + 1):
            valid, want = np.flatnonzero((xr >= a) & (yr <= c)), set()
            for i in range(1, len(valid)):
                j, before = int(valid[i]), valid[:i]
                d = kernels.dist2(v, before, v[j])
                order = np.argsort(d, kind="stable")
                want |= {e for u in kernels.diversify(v, before[order], d[order], m) for e in ((j, u), (u, j))}
            assert {(u, w) for u, w, l, r, b, _ in rows if l <= a <= r and b <= c} == want
    spans = {}
    for u, w, l, r, *_ in sorted(rows):
        assert spans.get((u, w), -2) + 1 < l  # an edge that stays is not ended and begun again
        spans[u, w] = r


def test_a_search_by_levels_finds_what_a_walk_finds():
    rng = np.random.default_rng(9)
    n = 200
    v, xr = rng.normal(size=(n, 4)), rng.permutation(n)
    rows, _, _ = kernels.build(v, np.arange(n), xr, np.arange(n), 6, "practical", 60)
    graph, q = kernels.Growing(n), rng.normal(size=4)
    for src, *edge, _ in rows:
        graph.add(src, tuple(edge))
    d, start = kernels.dist2(v, np.arange(n), q), int(xr.argmax())
    for a in (0, 60, 150):
        assert kernels.spread(graph, d, a, start, n).tolist() == kernels.walk(v, graph, q, a, n, start, n)[0]
        valid = np.flatnonzero(xr >= a)
        assert kernels.spread(graph, d, a, start, 30)[:10].tolist() == valid[np.argsort(d[valid])][:10].tolist()
