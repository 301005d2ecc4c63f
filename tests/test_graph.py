"""Relations, kernels and searches against plain Python."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from ivsearch.functions import coords, relations
from ivsearch.operators import audit, exact, index, kernels, measure
from ivsearch.sources import vecfiles

TOY = [(0, [0.0, 0.0], 1, 4), (1, [4.0, 0.0], 3, 5), (2, [1.0, 1.0], 2, 7), (3, [5.0, 1.0], 6, 8), (4, [2.0, 3.0], 4, 9), (5, [6.0, 4.0], 5, 9)]
DDL = "oid long, vec array<double>, s double, t double"


def tied(n=40, seed=1):
    r = np.random.default_rng(seed)
    s = r.integers(0, 20, n)
    return r.integers(0, 50, (n, 3)).astype(float), s, s + r.integers(0, 12, n)


def frame(spark, rows):
    return spark.createDataFrame([(int(a), [float(x) for x in v], float(s), float(t)) for a, v, s, t in rows], DDL)


def test_relations():
    with pytest.raises(relations.UnsupportedRelation):
        relations.custom("s>sq", "t<=tq")
    with pytest.raises(relations.UnsupportedRelation):
        relations.custom("s>=sq")
    assert relations.AFTER.plan().signs == (1, -1) and relations.BEFORE.plan().signs == (-1, 1)


@pytest.mark.parametrize("swap", [False, True])
@pytest.mark.parametrize("rel", list(relations.ALL))
def test_mapping_and_states(spark, rel, swap):
    r = relations.ALL[rel]
    o = frame(spark, TOY)
    q = spark.createDataFrame([(i, float(a), float(b)) for i, (a, b) in enumerate([(2.5, 8.5), (4.5, 5.5), (0, 20), (9, 9), (-1, 0), (3, 5)])], "qid long, sq double, tq double")
    plain = {tuple(x) for x in o.join(q, r.predicate()).select("qid", "oid").collect()}
    plan = r.plan(swap)
    ax, aq = coords.attach(o, plan), coords.attach_queries(q, plan)
    assert plain == {tuple(x) for x in ax.join(aq, (F.col("x") >= F.col("xq")) & (F.col("y") <= F.col("yq"))).select("qid", "oid").collect()}
    assert plain == {tuple(x) for x in ax.join(coords.snap(aq, ax), (F.col("x") >= F.col("a")) & (F.col("y") <= F.col("c"))).select("qid", "oid").collect()}
    for method in ("broadcast", "dominance") + (("bucketed",) if rel == "overlaps" else ()):
        got = [tuple(x) for x in exact.interval_join(o, q, r, method, 3).collect()]
        assert sorted(got) == sorted(plain)


@pytest.mark.parametrize("sx,sy", [(1, 1), (1, -1), (-1, 1), (-1, -1)])
def test_active_graph_is_the_dedicated_one(sx, sy):
    v, s, t = tied()
    x, y = sx * s, sy * t
    oid = np.arange(len(v))
    order = np.lexsort((oid, y))
    v, x, y, oid = v[order], x[order], y[order], oid[order]
    xr, yr = (np.unique(z, return_inverse=True)[1] for z in (x, y))
    rows, _, _ = kernels.build(v, oid, xr, yr, 4)
    for a in range(xr.max() + 1):
        for c in range(yr.max() + 1):
            active = {(u, w) for u, w, l, r, b, _ in rows if l <= a <= r and b <= c}
            assert active == kernels.dedicated(v, oid, xr, yr, a, c, 4)


def test_worked_example():
    v = np.array([r[1] for r in TOY])
    xr, yr = (np.unique([r[i] for r in TOY], return_inverse=True)[1] for i in (2, 3))
    rows, rounds, _ = kernels.build(v, np.arange(6), xr, yr, 2)
    assert rounds == 11 and len(rows) == 26


@pytest.mark.parametrize("leap", ["full", "conservative", "aggressive", "max"])
def test_anchored_patches_connect_every_state(leap):
    v, s, t = tied(60, 3)
    order = np.lexsort((np.arange(60), t))
    v, xr, yr = v[order], np.unique(s[order], return_inverse=True)[1], np.unique(t[order], return_inverse=True)[1]
    rows, _, open_ = kernels.build(v, order, xr, yr, 4, "practical", 6, leap, "anchored", 2)
    assert open_ <= 60
    for a in range(xr.max() + 1):
        for c in range(yr.max() + 1):
            valid = set(np.flatnonzero((xr >= a) & (yr <= c)).tolist())
            edges = [(u, w) for u, w, l, r, b, _ in rows if l <= a <= r and b <= c]
            assert all(u in valid and w in valid for u, w in edges)
            seen, todo = set(), list(valid)[:1]
            while todo:
                x = todo.pop()
                if x not in seen:
                    seen.add(x)
                    todo += [w for u, w in edges if u == x]
            assert seen == valid


def test_patches_raise_recall(spark):
    r = np.random.default_rng(5)
    n = 300
    s = r.integers(0, 1000, n)
    o = frame(spark, zip(range(n), r.normal(size=(n, 8)), s, s + r.integers(0, 400, n))).cache()
    q = spark.createDataFrame([(i, r.normal(size=8).tolist(), float(a), float(a + 450), 10) for i, a in enumerate(r.integers(500, 900, 30))], "qid long, qvec array<double>, sq double, tq double, k int")
    truth = exact.filtered_knn(o, q, relations.CONTAINED)
    mean = {}
    for patch in ("none", "anchored"):
        g = index.build(o, relations.CONTAINED, 4, "practical", 12, patch=patch, kp=4).cache()
        assert audit.broken_labels(g).count() == 0
        mean[patch] = measure.recall(index.search(g, q, relations.CONTAINED, 300), truth).agg(F.avg("recall")).first()[0]
    assert mean["anchored"] == 1.0 >= mean["none"]


def test_bad_objects_and_no_objects(spark):
    rows = spark.createDataFrame([(1, [1.0, 2.0], 1.0, 2.0), (2, None, 1.0, 2.0), (3, [1.0, None], 1.0, 2.0), (4, [1.0, 1.0], 3.0, 2.0), (5, [1.0, 1.0], float("nan"), 2.0), (6, [1.0, 1.0], None, 2.0)], DDL)
    good, bad = coords.accept(rows)
    assert [r.oid for r in good.collect()] == [1] and bad.count() == 5
    q = spark.createDataFrame([(0, [0.0, 0.0], 0.0, 9.0, 3)], "qid long, qvec array<double>, sq double, tq double, k int")
    g = index.build(rows, relations.CONTAINED)
    assert [r.oid for r in index.search(g, q, relations.CONTAINED).collect()] == [1]
    none = index.build(rows.limit(0), relations.CONTAINED)
    assert index.search(none, q, relations.CONTAINED).count() == 0


def test_vector_files(spark, tmp_path):
    v = np.arange(12, dtype=np.float32).reshape(3, 4)
    (tmp_path / "a.fvecs").write_bytes(vecfiles.write_rows(v))
    got = vecfiles.read(spark, str(tmp_path / "a.fvecs")).orderBy("oid").collect()
    assert [r.vec for r in got] == v.tolist()
