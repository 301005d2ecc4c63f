"""Shards dealt to tasks."""

import numpy as np
from pyspark.sql import functions as F

from ivsearch.functions import relations
from ivsearch.operators import index
from test_wide import shard


def test_tasks_get_as_many_shards_as_others(spark):
    rng = np.random.default_rng(4)
    o = spark.createDataFrame([(i, rng.normal(size=3).tolist(), float(i % 50), float(i % 50 + 9)) for i in range(600)], "oid long, vec array<double>, s double, t double")
    g = index.build(o, relations.CONTAINED, 4, "practical", 20, shard_rows=20)
    for df in (g, index.pack(g)):
        held = [r["count"] for r in df.select("shard", F.spark_partition_id().alias("task")).distinct().groupBy("task").count().collect()]
        assert sum(held) == 30 and len(held) == spark.sparkContext.defaultParallelism and max(held) - min(held) <= 1


def test_answers_without_costs_are_those_with_them():
    s, rng = shard()
    q, xq, yq, k = rng.normal(size=(70, 4)), rng.integers(-2, 43, 70).astype(float), rng.integers(-2, 43, 70).astype(float), rng.integers(1, 30, 70)
    for mode in ("walk", "post", "predicate"):
        for scan_below in (0, 9):
            whole, bare = (s.find_many(q, xq, yq, k, mode, scan_below, c) for c in (True, False))
            assert all(np.array_equal(x, y) for x, y in zip(whole[:3], bare[:3])) and not bare[3].any()
