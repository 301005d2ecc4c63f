"""Walks of bounded pools, side by side."""

import numpy as np
import pytest

from ivsearch.functions.relations import CONTAINED, OVERLAPS
from ivsearch.operators import blobs, index, interval_tree, kernels
from test_wide import frames


def shard(whole: bool, n=200, seed=3):
    """With whole numbers as components many distances are equal."""
    rng = np.random.default_rng(seed)
    v = rng.integers(0, 4, (n, 3)).astype(float) if whole else rng.normal(size=(n, 4))
    x, y, oid = rng.integers(0, 40, n).astype(float), np.sort(rng.integers(0, 40, n)).astype(float), np.arange(n)
    xr, yr = (np.unique(z, return_inverse=True)[1] for z in (x, y))
    lists = [[] for _ in range(n)]
    for src, *edge in kernels.build(v, oid, xr, yr, 4, "practical", 12)[0]:
        lists[src].append(edge[:4])
    flat = np.array([e for own in lists for e in own], np.int32).reshape(-1, 4)
    ends = np.concatenate([[0], np.cumsum([len(own) for own in lists])]).astype(np.int64)
    return index.Shard(blobs.pack(oid=oid, v=v, x=x, y=y, ends=ends, dst=flat[:, 0], l=flat[:, 1], r=flat[:, 2], b=flat[:, 3])), rng


@pytest.mark.parametrize("whole", [False, True])
def test_bounded_walks_side_by_side_are_single_walks(whole):
    s, rng = shard(whole)
    q = rng.integers(0, 4, (150, 3)).astype(float) if whole else rng.normal(size=(150, 4))
    xq, yq, k = rng.integers(-2, 43, 150).astype(float), rng.integers(-2, 43, 150).astype(float), rng.integers(1, 30, 150)
    met = 0
    for mode in ("walk", "post", "dense"):
        for ef, scan_below in ((1, 0), (7, 0), (20, 9), (1000, 0)):
            rows, ids, dist, costs = s.walk_many(q, xq, yq, k, ef, mode, scan_below, 5)
            for i in range(150):
                one = s.find(q[i], xq[i], yq[i], int(k[i]), ef, mode, scan_below, 5)
                assert one[0].tolist() == ids[rows == i].tolist() and one[1].tolist() == dist[rows == i].tolist(), (mode, ef, i)
                assert tuple(one[2]) == tuple(costs[i]), (mode, ef, i)
            met += len(ids)
    assert met > 1000 and s.walk_many(q, xq, yq, k, 7, "predicate", 0, 5) is None


def test_walks_in_parts_are_the_same():
    s, rng = shard(False)
    q, start = rng.normal(size=(40, 4)), rng.integers(0, 200, 40)
    whole = kernels.walk_many(s.v, s.ends, s.edges[0], q, start, 6)
    parts = [kernels.walk_many(s.v, s.ends, s.edges[0], q[i : i + 1], start[i : i + 1], 6) for i in range(40)]
    assert whole[1].tolist() == np.concatenate([p[1] for p in parts]).tolist() and whole[2].tolist() == np.concatenate([p[2] for p in parts]).tolist()
    many = 2 + (1 << 24) // 200  # more marks than are held at once
    twice = kernels.walk_many(s.v, s.ends, s.edges[0], np.repeat(q[:1], many, 0), np.repeat(start[:1], many), 2)
    assert len(np.unique(twice[1])) == 2 and (np.bincount(twice[0]) == 2).all() and (twice[2] == twice[2][0]).all()


@pytest.mark.parametrize("whole", [False, True])
def test_baselines_walk_side_by_side_as_alone(spark, whole):
    rng = np.random.default_rng(4)
    vec = lambda: (rng.integers(0, 4, 4) if whole else rng.normal(size=4)).astype(float).tolist()
    rows = [(i, vec(), float(a), float(a + b)) for i, (a, b) in enumerate(zip(rng.integers(0, 60, 300), rng.integers(0, 30, 300)))]
    o = spark.createDataFrame(rows, "oid long, vec array<double>, s double, t double")
    q, xq = np.array([vec() for _ in range(80)]), rng.integers(-5, 60, 80).astype(float)
    yq, k = xq + rng.integers(5, 90, 80), rng.integers(1, 30, 80)
    tree = interval_tree.Tree(interval_tree.build(o, 16, 4, 20).first().blob)
    layered = interval_tree.Layered(interval_tree.build_layered(o, OVERLAPS, 4, 20).first().blob)
    for s in (tree, layered):
        for ef in (1, 8, 40):
            at, ids, dist, costs = s.walk_many(q, xq, yq, k, ef)
            for i in range(80):
                one = s.take(q[i], xq[i], yq[i], int(k[i]), ef)
                assert one[0].tolist() == ids[at == i].tolist() and one[1].tolist() == dist[at == i].tolist(), (type(s), ef, i)
                assert tuple(one[2]) == tuple(costs[i]), (type(s), ef, i)
            assert len(ids)


def test_searches_walk_no_query_alone(spark):
    o, q, _ = frames(spark)
    packed = spark.createDataFrame(index.pack(index.build(o, CONTAINED, 4, "practical", 20, shard_rows=100)).collect(), index.PACKED).coalesce(1)

    def alone(*_):
        raise AssertionError("a query walked alone")

    asked = index.attach_queries(q, CONTAINED.plan())
    many = lambda s, v, xq, yq, k: s.walk_many(v, xq, yq, k, 12, "walk", 0, 16)
    found = index.each_shard(packed, asked, alone, many=many)
    held = found.where("oid is not null").groupBy("qid").count().collect()
    assert held and max(r["count"] for r in held) <= 5  # a task merges its shards' answers, with costs too
    paid = {r.qid: (r.evals, r.hops, r.tests) for r in found.where("oid is null").collect()}
    assert len(paid) == found.where("oid is null").count()  # one row of costs a query
    single = index.each_shard(packed, asked, lambda s, v, xq, yq, k: s.find(v, xq, yq, k, 12, "walk", 0, 16))
    assert paid == {r.qid: (r.evals, r.hops, r.tests) for r in single.where("oid is null").collect()}
    assert sorted(map(tuple, found.collect()), key=str) == sorted(map(tuple, single.collect()), key=str)


def test_index_rows_take_edges_as_they_are_found():
    v, x, y = np.arange(6.0).reshape(3, 2), np.array([1.0, 0.0, 1.0]), np.array([0.0, 2.0, 2.0])
    edges = [(1, 0, 0, 1, 2, 0), (0, 1, 0, 1, 2, 0), (1, 2, 1, 1, 2, 1), (0, 2, 3, 4, 5, 0)]
    t = index._rows(4, v, np.array([7, 8, 9]), x, y, np.array([1, 0, 1]), np.array([0, 1, 1]), edges, 5, 6).to_pylist()
    assert [r["dst"] for r in t] == [[1, 2], [0, 2], []] and [r["l"] for r in t] == [[0, 3], [0, 1], []] and [r["kind"] for r in t] == [[0, 0], [0, 1], []]
    assert [r["vec"] for r in t] == v.tolist() and [r["rounds"] for r in t] == [5, 0, 0] and [r["uncovered"] for r in t] == [6, 0, 0]
    assert index._rows(0, v[:1], np.array([7]), x[:1], y[:1], np.zeros(1, int), np.zeros(1, int), []).to_pylist()[0]["dst"] == []
