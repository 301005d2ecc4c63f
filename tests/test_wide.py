"""Distances as SQL engines sum them, and searches whose pool holds a whole shard."""

import numpy as np

from ivsearch.operators import joins


def in_order(a, b):
    total = 0.0
    for x, y in zip(a.tolist(), b.tolist()):
        total += (x - y) * (x - y)
    return total**0.5


def test_distances_are_summed_in_order():
    rng = np.random.default_rng(5)
    q, v = rng.normal(size=(4, 64)), rng.normal(size=(300, 64))
    rows, cols, dist = joins.nearest_in(q, v, np.arange(300), 20)
    assert len(rows) == 80 and dist.tolist() == [in_order(q[i], v[j]) for i, j in zip(rows, cols)]


def test_nearest_with_a_mask_and_a_k_for_each():
    rng = np.random.default_rng(6)
    q, v, oid = rng.integers(0, 3, (5, 3)).astype(float), rng.integers(0, 3, (200, 3)).astype(float), rng.permutation(200)
    allowed, k = rng.random((5, 200)) < [[0.5], [0.02], [0], [1], [0.5]], np.array([3, 50, 4, 1, 0])
    rows, cols, dist = joins.nearest_in(q, v, oid, k, allowed)
    want = [(i, d, o) for i in range(5) for d, o in sorted((in_order(q[i], v[j]), int(oid[j])) for j in np.flatnonzero(allowed[i]))[: k[i]]]
    assert [(int(i), d, int(oid[j])) for i, j, d in zip(rows, cols, dist)] == want


def shard(n=120, seed=3):
    from ivsearch.operators import blobs, index, kernels

    rng = np.random.default_rng(seed)
    v, x, y = rng.normal(size=(n, 4)), rng.integers(0, 40, n).astype(float), np.sort(rng.integers(0, 40, n)).astype(float)
    oid = np.arange(n)
    xr, yr = (np.unique(z, return_inverse=True)[1] for z in (x, y))
    lists = [[] for _ in range(n)]
    for src, *edge in kernels.build(v, oid, xr, yr, 4, "practical", 12)[0]:
        lists[src].append(edge[:4])
    flat = np.array([e for own in lists for e in own], np.int32).reshape(-1, 4)
    ends = np.concatenate([[0], np.cumsum([len(own) for own in lists])]).astype(np.int64)
    return index.Shard(blobs.pack(oid=oid, v=v, x=x, y=y, ends=ends, dst=flat[:, 0], l=flat[:, 1], r=flat[:, 2], b=flat[:, 3])), rng


def test_walking_all_queries_at_once_is_walking_each():
    s, rng = shard()
    q, xq, yq, k = rng.normal(size=(150, 4)), rng.integers(-2, 43, 150).astype(float), rng.integers(-2, 43, 150).astype(float), rng.integers(1, 30, 150)
    for mode in ("walk", "post", "predicate"):
        for scan_below in (0, 9):
            rows, ids, dist, costs = s.find_many(q, xq, yq, k, mode, scan_below)
            for i in range(150):
                one = s.find(q[i], xq[i], yq[i], int(k[i]), 1 << 20, mode, scan_below, 16)
                assert one[0].tolist() == ids[rows == i].tolist() and one[1].tolist() == dist[rows == i].tolist(), (mode, i)
                assert tuple(one[2]) == tuple(costs[i]), (mode, i)


def test_baselines_walk_all_queries_at_once(spark):
    from pyspark.sql import functions as F

    from ivsearch.functions.relations import CONTAINED
    from ivsearch.operators import exact, interval_tree

    rng = np.random.default_rng(4)
    rows = [(i, rng.normal(size=4).tolist(), float(a), float(a + b)) for i, (a, b) in enumerate(zip(rng.integers(0, 60, 300), rng.integers(0, 30, 300)))]
    o = spark.createDataFrame(rows, "oid long, vec array<double>, s double, t double")
    q = o.where("oid % 7 = 3").select(F.col("oid").alias("qid"), F.col("vec").alias("qvec"), (F.col("s") - 9).alias("sq"), (F.col("t") + 9).alias("tq"), F.lit(5).alias("k"))
    tree, layered = interval_tree.build(o, 16, 4, 20), interval_tree.build_layered(o, CONTAINED, 4, 20)
    ordered = lambda df, *c: [tuple(r) for r in df.select("qid", "rank", "oid", *c).orderBy("qid", "rank").collect()]
    want = ordered(exact.filtered_knn(o, q, CONTAINED))
    for many, one in ((interval_tree.search(tree, q, 300, True), interval_tree.search(tree, q, 299, True)), (interval_tree.search_layered(layered, q, CONTAINED, 300, True), interval_tree.search_layered(layered, q, CONTAINED, 299, True))):
        assert ordered(many) == want
        assert ordered(many, "evals", "hops", "tests")[:1] and [r[0] for r in ordered(one)] == [r[0] for r in want]


def frames(spark, n=260, seed=8):
    from pyspark.sql import functions as F

    rng = np.random.default_rng(seed)
    rows = [(i, rng.normal(size=4).tolist(), float(a), float(a + b)) for i, (a, b) in enumerate(zip(rng.integers(0, 60, n), rng.integers(0, 30, n)))]
    rows += [(n, [1.0, 2.0], 10.0, 12.0), (n + 1, None, 10.0, 12.0)]  # another length, no vector: never an answer
    o = spark.createDataFrame(rows, "oid long, vec array<double>, s double, t double")
    q = o.where(f"oid % 7 = 3 and oid < {n}").select(F.col("oid").alias("qid"), F.col("vec").alias("qvec"), (F.col("s") - 6).alias("sq"), (F.col("t") + 6).alias("tq"), F.lit(5).alias("k"))
    return o, q, rows[:n]


def brute(rows, valid, pad=6):
    out = []
    for i, v, s, t in rows:
        if i % 7 == 3:
            near = sorted((in_order(np.array(v), np.array(w)), j) for j, w, a, b in rows if valid(a, b, s - pad, t + pad))[:5]
            out += [(i, n + 1, j) for n, (_, j) in enumerate(near)]
    return out


def test_pair_baselines_on_odd_vectors(spark):
    from ivsearch.functions.relations import CONTAINED
    from ivsearch.operators import exact

    o, q, rows = frames(spark)
    want = brute(rows, lambda s, t, a, b: s >= a and t <= b)
    for how in (exact.prefilter, exact.two_scalar):
        assert [tuple(r) for r in how(o, q, CONTAINED).select("qid", "rank", "oid").orderBy("qid", "rank").collect()] == want


def test_any_predicate_by_lists_that_grow(spark):
    from pyspark.sql import functions as F

    from ivsearch.operators import exact

    o, q, rows = frames(spark)
    o = o.where("size(vec) = 4")
    found = exact.by_predicate(o, q, (F.col("s") > F.col("sq")) & (F.col("t") < F.col("tq")), (6, 12))
    assert [tuple(r) for r in found.select("qid", "rank", "oid").orderBy("qid", "rank").collect()] == brute(rows, lambda s, t, a, b: s > a and t < b)


def test_table_function_on_blocks_takes_any_size(spark):
    from pyspark.sql import functions as F

    from ivsearch.functions.relations import CONTAINED
    from ivsearch.operators import index
    from ivsearch.plans import sqlapi

    o, q, rows = frames(spark)
    index.pack(index.build(o, CONTAINED, 4, "practical", 20, shard_rows=100)).createOrReplaceTempView("t_shards")
    sqlapi.interval_knn_blocks(spark, CONTAINED, "t_blocks_knn")
    q.groupBy().agg(*[F.collect_list(c).alias(f"{c}s") for c in ("qid", "qvec", "sq", "tq")]).createOrReplaceTempView("t_blocks")
    found = spark.sql("SELECT f.* FROM t_shards CROSS JOIN t_blocks, LATERAL t_blocks_knn(blob, qids, qvecs, sqs, tqs, 5, 1000) f").collect()
    by = {}
    for r in found:
        by.setdefault(r.qid, []).append((r.dist, r.oid))
    assert [(i, n + 1, j) for i in sorted(by) for n, (_, j) in enumerate(sorted(by[i])[:5])] == brute(rows, lambda s, t, a, b: s >= a and t <= b)


def test_frontier_keeps_equal_points(spark):
    from ivsearch.operators import measure

    rows = [("a", "walk", 0.9, 5.0), ("a", "scan", 0.9, 5.0), ("a", "walk", 0.9, 4.0), ("a", "walk", 1.0, 3.0), ("a", "post", 0.95, 3.0), ("b", "walk", 0.5, 1.0)]
    found = measure.pareto(spark.createDataFrame(rows, "dataset string, method string, recall double, qps double"), ["dataset"])
    assert sorted(tuple(r) for r in found.collect()) == sorted([rows[0], rows[1], rows[3], rows[5]])


def test_report_points_come_from_a_table(spark, tmp_path):
    from ivsearch.plans import queries

    cols = "l_returnflag string, l_linestatus string, l_linenumber int, l_discount double, l_extendedprice double"
    spark.createDataFrame([("N", "O", 3, 0.06, 12.5), ("N", "O", 1, 0.0, 7.0), ("A", "F", 2, 0.1, 9.0)], cols).write.parquet(f"{tmp_path}/lineitem.parquet")
    assert sorted(tuple(r) for r in queries.points(spark, str(tmp_path)).collect()) == [("A", "F", "post", 0.9, 9.0), ("N", "O", "scan", 1.0, 7.0), ("N", "O", "walk", 0.94, 12.5)]


def test_a_task_merges_its_shards(spark):
    from ivsearch.functions.relations import CONTAINED
    from ivsearch.operators import index

    o, q, rows = frames(spark)
    packed = spark.createDataFrame(index.pack(index.build(o, CONTAINED, 4, "practical", 20, shard_rows=40)).collect(), index.PACKED).coalesce(1)
    assert packed.count() > 3
    want = brute(rows, lambda s, t, a, b: s >= a and t <= b)
    asked = index.attach_queries(q, CONTAINED.plan())
    found = index.each_shard(packed, asked, lambda s, v, xq, yq, k: s.find(v, xq, yq, k, 1000, "walk", 0, 16), costs=False)
    assert found.count() == len(want)  # k a query, not k a query and shard
    for df in (index.search(packed, q, CONTAINED, 1000), index.search(packed, q, CONTAINED, 1000, stats=True)):
        assert [tuple(r) for r in df.select("qid", "rank", "oid").orderBy("qid", "rank").collect()] == want
