"""Bad input, endpoint types, the store, workloads, planner, appends and SQL, against plain Python."""

import datetime as dt
from decimal import Decimal

import numpy as np
import pytest
from pyspark.sql import functions as F

from ivsearch.functions import coords, relations
from ivsearch.operators import audit, blobs, exact, index, interval_tree, joins, kernels, measure, stats
from ivsearch.plans import experiments, sqlapi, workload
from ivsearch.sources import tables
from ivsearch.streaming.append import Appender

R = np.random.default_rng(11)
V = R.normal(size=(300, 6))
S = R.integers(0, 900, 300)
T = S + R.integers(0, 300, 300)
DDL, QDDL = "oid long, vec array<double>, s double, t double", "qid long, qvec array<double>, sq double, tq double, k int"
ASKED = [(i, V[i * 7].tolist(), float(a), float(a + w), 5) for i, (a, w) in enumerate([(100, 300), (0, 1200), (500, 90), (880, 5), (-50, 10), (200, 700)])]


@pytest.fixture(scope="module")
def objects(spark):
    return spark.createDataFrame([(i, V[i].tolist(), float(S[i]), float(T[i])) for i in range(300)], DDL).repartition(3).cache()


@pytest.fixture(scope="module")
def queries(spark):
    return spark.createDataFrame(ASKED, QDDL)


def near(relation, ids=range(300)):
    """(qid, rank, oid) by brute force."""
    out = []
    for qid, q, a, b, k in ASKED:
        at = {"sq": a, "tq": b}
        ok = [i for i in ids if all((end[i] >= at[t.query]) if t.op == ">=" else (end[i] <= at[t.query]) for t in relation.terms for end in [{"s": S, "t": T}[t.end]])]
        out += [(qid, r + 1, i) for r, i in enumerate(sorted(ok, key=lambda i: (((V[i] - q) ** 2).sum(), i))[:k])]
    return out


def ranks(df):
    return sorted((r.qid, r["rank"], r.oid) for r in df.collect())


@pytest.mark.parametrize("rel", list(relations.ALL))
def test_search_and_truth(objects, queries, rel):
    r = relations.ALL[rel]
    want = near(r)
    assert ranks(exact.filtered_knn(objects, queries, r)) == want
    packed = index.pack(index.build(objects, r, 6, "practical", 40, shard_rows=120)).cache()
    assert ranks(index.search(packed, queries, r, 400)) == want and ranks(index.search(packed, queries, r, 400, scan_below=60)) == want


@pytest.mark.parametrize("how", [{"method": "incremental", "pool": 400}, {"pool_by": "graph", "pool": 400}, {"method": "exact"}])
def test_constructors(objects, queries, how):
    g = index.build(objects, relations.OVERLAPS, 6, shard_rows=1000, **how).cache()
    assert audit.broken_labels(g).count() == 0 and ranks(index.search(g, queries, relations.OVERLAPS, 400)) == near(relations.OVERLAPS)


def test_endpoint_types(spark, objects, queries):
    """Dates, timestamps and decimals give what numbers give, for all relations."""
    day = dt.datetime(2020, 1, 1)
    kinds = {
        "date": lambda x: (day + dt.timedelta(days=int(x))).date(), "timestamp": lambda x: day + dt.timedelta(days=int(x)), "decimal(20,4)": lambda x: Decimal(int(x)),
    }
    rows, asked = objects.collect(), queries.collect()
    for kind, to in kinds.items():
        o = spark.createDataFrame([(r.oid, r.vec, to(r.s), to(r.t)) for r in rows], f"oid long, vec array<double>, s {kind}, t {kind}")
        q = spark.createDataFrame([(r.qid, r.qvec, to(r.sq), to(r.tq), r.k) for r in asked], f"qid long, qvec array<double>, sq {kind}, tq {kind}, k int")
        for r in relations.ALL.values():
            assert ranks(exact.filtered_knn(o, q, r)) == near(r)
        g = index.build(o, relations.AFTER, 6, "practical", 40)
        assert ranks(index.search(g, q, relations.AFTER, 400)) == near(relations.AFTER)


def test_odd_objects(spark, objects, queries):
    """Ragged, infinite and repeated rows: left out or taken once, the same in every run."""
    inf = float("inf")
    odd = spark.createDataFrame([(900, [1.0, 2.0], 0.0, 5.0), (901, [inf] * 6, 0.0, 5.0), (902, V[0].tolist(), -inf, 5.0), (903, V[0].tolist(), 0.0, inf), (None, V[0].tolist(), 0.0, 5.0), (7, (V[7] + 9).tolist(), 2000.0, 2001.0), (8, V[8].tolist(), float(S[8]), float(T[8]))], DDL)
    g = index.build(objects.union(odd), relations.CONTAINED, 6, "practical", 400)
    assert g.count() == 300 and ranks(index.search(g, queries, relations.CONTAINED, 400)) == near(relations.CONTAINED)
    strange = spark.createDataFrame([(50, [1.0], 0.0, 9.0, 3), (51, None, 0.0, 9.0, 3), (52, V[0].tolist(), None, 9.0, 3)], QDDL)
    assert index.search(g, strange, relations.CONTAINED).count() == 0
    assert exact.filtered_knn(objects.limit(0), queries, relations.CONTAINED).count() == 0 and exact.filtered_knn(objects, queries.limit(0), None).count() == 0


def test_store(spark, objects, queries, tmp_path):
    g = index.build(objects, relations.COVERS, 6, "practical", 400, shard_rows=120).cache()
    index.save(g, str(tmp_path / "i"), relations.COVERS, m=6)
    first = index.load(spark, str(tmp_path / "i"))[2]
    index.save(index.build(objects, relations.BEFORE, 6, "practical", 400), str(tmp_path / "i"), relations.BEFORE, m=6, note="second")
    held, relation, params = index.load(spark, str(tmp_path / "i"))
    assert first == {"m": "6"} and params["note"] == "second" and relation.terms == relations.BEFORE.terms
    assert ranks(index.search(held["shards"], queries, relation, 400)) == near(relations.BEFORE)
    plan = index.search(held["shards"], queries, relation, 400)._jdf.queryExecution().executedPlan().toString()
    assert "CoGroup" not in plan and "Join" not in plan  # shards stay where they are
    with pytest.raises(ValueError):
        index.load(spark, str(tmp_path / "i"), "no such version")
    parts = {"a": np.arange(5, dtype=np.int32), "b": R.normal(size=(3, 2)), "c": np.zeros((0, 4), np.int64)}
    assert all((x == parts[k]).all() and x.dtype == parts[k].dtype and x.shape == parts[k].shape for k, x in blobs.unpack(blobs.pack(**parts)).items())


def test_baselines(objects, queries):
    want = near(relations.CONTAINED)
    assert ranks(interval_tree.search(interval_tree.build(objects, 20, 6, 400, 120), queries, 400)) == want
    assert ranks(interval_tree.search_layered(interval_tree.build_layered(objects, relations.CONTAINED, 6, 400, 120), queries, relations.CONTAINED, 400)) == want
    dense = index.unlabelled(objects, relations.CONTAINED, 8, shard_rows=1000, gamma=12)
    got = index.search(dense, queries, relations.CONTAINED, 400, mode="dense", stats=True, fan=1000).collect()
    assert len(got) >= 0.9 * len(want) and {(r.qid, r["rank"], r.oid) for r in got} & set(want)
    assert all(r.evals >= 1 and r.hops >= 1 for r in got)
    assert ranks(exact.two_scalar(objects, queries, relations.OVERLAPS)) == near(relations.OVERLAPS)
    some = exact.two_scalar(objects, queries, relations.OVERLAPS, depth=40)
    assert {(r.qid, r.oid) for r in some.collect()} <= {(r.qid, r.oid) for r in objects.join(queries, relations.OVERLAPS.predicate()).collect()}


@pytest.mark.parametrize("rel", list(relations.ALL))
def test_exact_count(objects, rel):
    """Realised counts are what they say, ties included; every query is reached or listed."""
    r = relations.ALL[rel]
    asked = objects.where("oid % 10 = 3").select(F.col("oid").alias("qid"), F.col("vec").alias("qvec"))
    made, lost = workload.exact_count(objects, asked, r, 0.1)
    rows = made.collect()
    got = {x.qid: x.valid for x in measure.selectivity(objects, made, r).collect()}
    assert len(rows) + lost.count() == 30 and all(got[x.qid] == x.realised >= x.target == 30 and x.sq <= x.tq and x.in_bucket == (x.realised - 30 <= 3) for x in rows)
    none, all_lost = workload.exact_count(objects.limit(0), asked, r, 0.1)
    assert none.count() == 0 and all_lost.count() == 30


def test_planner_and_grid(objects, queries):
    shards = index.pack(index.build(objects, relations.CONTAINED, 6, "practical", 400)).cache()
    got, how = sqlapi.planned(objects, shards, queries, relations.CONTAINED, 40, 400, 8)
    assert ranks(got) == near(relations.CONTAINED) and {r.how for r in how.collect()} == {"empty", "scan", "walk"}
    plan = relations.CONTAINED.plan()
    counts, frame = stats.grid(coords.attach(objects, plan), 8)
    valid = {r.qid: r.valid for r in measure.selectivity(objects, queries, relations.CONTAINED).collect()}
    assert all(r.low <= valid[r.qid] <= r.high for r in stats.bounds(coords.attach_queries(queries, plan), counts, frame, 8).collect())
    assert {(r.oid, r.n) for r in stats.density(coords.attach(objects, plan), 50.0).collect()} == {(i, int(((T >= T[i] - 50) & (T <= T[i])).sum())) for i in range(300)}


def test_asof(spark):
    left = spark.createDataFrame([(i, float(x) if x is not None else None) for i, x in enumerate([-5, 0, 3, 3, 7, 100, None, 51])], "id int, at double")
    right = spark.createDataFrame([(float(x),) for x in [0, 3, 3, 8, 50]], "val double")
    ahead = {r.id: r.found for r in joins.asof(left, right, "at", "val", "forward", 4).collect()}
    behind = {r.id: r.found for r in joins.asof(left, right, "at", "val", "backward", 4).collect()}
    assert ahead == {0: 0.0, 1: 0.0, 2: 3.0, 3: 3.0, 4: 8.0, 5: None, 6: None, 7: None}
    assert behind == {0: None, 1: 0.0, 2: 3.0, 3: 3.0, 4: 3.0, 5: 50.0, 6: None, 7: 50.0}
    assert {r.found for r in joins.asof(left, right.limit(0), "at", "val").collect()} == {None}
    assert spark.range(3).select(joins.cell_of(F.col("id").cast("double"), [0.5, 1.0, 1.5])).collect() == [(0,), (2,), (3,)]


def test_kernels_agree():
    """Pools by blocks hold the nearest earlier objects, and pruning by a matrix keeps what pruning by differences keeps."""
    v = R.integers(0, 9, (120, 3)).astype(float)
    oid = R.permutation(120)
    for j, ids, d in kernels.pools(v, oid, 15, 32):
        want, far = kernels.earlier(v, oid, j)
        assert ids.tolist() == want[:15].tolist() and d.tolist() == far[:15].tolist()
        assert ids[kernels.keep(np.ones(len(ids), bool), kernels.closer(v, ids, d), 5)].tolist() == kernels.diversify(v, ids, d, 5)


def test_append(spark, objects, queries, tmp_path):
    a = Appender(spark, relations.CONTAINED, str(tmp_path / "a"), m=6, pool=400)
    parts = [objects.where("oid % 5 <> 0 and t < 500"), objects.where("oid % 5 <> 0 and t >= 500"), objects.where("oid % 5 = 0")]
    for i, p in enumerate(parts):
        a.add(p, i)
    a.add(parts[2], 2)
    assert ranks(a.search(queries, 400)) == near(relations.CONTAINED)


def test_query_stream(spark, objects, queries, tmp_path):
    from ivsearch.streaming.sessions import search_stream

    queries.write.parquet(str(tmp_path / "in"))
    shards = index.pack(index.build(objects, relations.CONTAINED, 6, "practical", 400)).cache()
    stream = spark.readStream.schema(queries.schema).parquet(str(tmp_path / "in"))
    running = search_stream(stream, shards, relations.CONTAINED, lambda df, n: df.write.mode("overwrite").parquet(str(tmp_path / f"out/{n}")), ef=400)
    running.processAllAvailable()
    running.stop()
    assert ranks(spark.read.parquet(str(tmp_path / "out/*"))) == near(relations.CONTAINED)


def test_late_events(spark, tmp_path):
    """Behind the watermark of a stream, late events of closed sessions are dropped."""
    from ivsearch.streaming.sessions import sessions

    at = lambda h: dt.datetime(2024, 1, 1) + dt.timedelta(hours=h)
    for i, hours in enumerate([(0, 1), (40, 41), (80, 81), (2, 120)]):
        spark.createDataFrame([(1, at(h)) for h in hours], "user_id long, ts timestamp").coalesce(1).write.parquet(str(tmp_path / f"in/{i}"))
    stream = spark.readStream.schema("user_id long, ts timestamp").option("maxFilesPerTrigger", 1).option("latestFirst", False).parquet(str(tmp_path / "in/*"))
    running = sessions(stream, "6 hours", "1 hour").writeStream.format("memory").queryName("closed").outputMode("append").start()
    running.processAllAvailable()
    running.stop()
    got = {(r.s, r.n) for r in spark.table("closed").collect()}
    assert {(at(0), 2), (at(40), 2)} <= got


def test_files_and_outside_class(spark, objects, queries, tmp_path):
    for kind in ("csv", "json", "orc"):
        tables.write_intervals(objects, str(tmp_path / kind), kind)
        assert sorted(map(tuple, tables.read_intervals(spark, str(tmp_path / kind), kind).collect())) == sorted((i, float(S[i]), float(T[i])) for i in range(300))
    with pytest.raises(relations.UnsupportedRelation):
        sqlapi.outside(["s>sq", "t<=tq"], objects, queries)
    assert sqlapi.outside(["s>sq", "t<=tq"], objects, queries, F.lit(False)).count() == 0


def test_measures(spark):
    x = experiments.table(spark, [("d", "r", 0.1, "walk", {"ef": "8"}, 5, 50, 0.9, 0, 3.0, 2.0, 1.0, 100.0, 1.0, 10, 160, 30)])
    assert x.count() == 1 and measure.by_method(x).columns[-1] == "walk"
