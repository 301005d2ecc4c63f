"""Measures of accuracy and cost, and reports over them."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..session import small


def recall(results: DataFrame, truth: DataFrame) -> DataFrame:
    """qid, hits, truth (its size), recall: the share of the true answers found; queries without valid objects are left out."""
    hit = truth.select("qid", "oid").join(results.select("qid", "oid", F.lit(1).alias("hit")), ["qid", "oid"], "left")
    return hit.groupBy("qid").agg(F.count("hit").alias("hits"), F.count(F.lit(1)).alias("truth")).withColumn("recall", F.col("hits") / F.col("truth"))


def seconds(run: Callable[[], DataFrame]) -> float:
    began = time.perf_counter()
    run().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def qps(run: Callable[[], DataFrame], queries: int) -> float:
    seconds(run)
    return queries / seconds(run)


def pareto(points: DataFrame, by: list[str]) -> DataFrame:
    """Points (recall, qps) of each group that no other one exceeds in one without falling behind in the other; equal points stay together.

    Only the fastest point of each recall can be on the frontier, so the window sees one row a group and recall, not the points.
    """
    fastest = points.groupBy(*by, "recall").agg(F.max("qps").alias("qps"))
    order = W.partitionBy(*by).orderBy(F.col("recall").desc()).rowsBetween(W.unboundedPreceding, -1)
    best = fastest.withColumn("_best", F.max("qps").over(order)).where(F.col("_best").isNull() | (F.col("qps") > F.col("_best"))).drop("_best")
    return points.join(best, [*by, "recall", "qps"], "left_semi").select(*points.columns)


def qps_at(points: DataFrame, least: float, by: list[str]) -> DataFrame:
    return points.where(F.col("recall") >= least).groupBy(*by).agg(F.max("qps").alias("qps"), F.max_by("params", "qps").alias("params"))


def normalised(points: DataFrame, base: str = "uniform") -> DataFrame:
    """qps of each distribution over that of the base one, same relation and selectivity."""
    keys = ["relation", "sigma"]
    own = points.where(F.col("distribution") == base).select(*keys, F.col("qps").alias("base_qps"))
    return points.join(own, keys).withColumn("ratio", F.col("qps") / F.col("base_qps"))


def index_size(index: DataFrame) -> DataFrame:
    """edges, bytes (four 32-bit numbers an edge and its kind; without vectors), objects, rounds, uncovered ranges, largest degree."""
    return index.agg(
        F.count(F.lit(1)).alias("objects"), F.sum(F.size("dst")).alias("edges"), F.sum(F.size("dst") * 17).alias("bytes"), F.sum("rounds").alias("rounds"),
        F.sum("uncovered").alias("uncovered"), F.max(F.size("dst")).alias("max_degree"), F.sum(F.size(F.filter("kind", lambda k: k == 1))).alias("patch_edges"),
    )


def report(points: DataFrame) -> DataFrame:
    """Mean recall over dataset, relation and method, with all subtotals."""
    return points.cube("dataset", "relation", "method").agg(F.count(F.lit(1)).alias("n"), F.avg("recall").alias("recall"))


def by_method(points: DataFrame, value: str = "recall") -> DataFrame:
    return points.groupBy("dataset", "relation", "sigma").pivot("method").agg(F.first(value))


def selectivity(objects: DataFrame, queries: DataFrame, relation) -> DataFrame:
    """qid, valid, sigma: the number of valid objects and its share of all, by counts of valid pairs in each task of objects."""
    from ..functions.coords import on_axis

    n = objects.count()
    o, q = on_axis(objects.select("oid", "s", "t"), "s", "t"), on_axis(queries.select("qid", "sq", "tq"), "sq", "tq")
    pairs = o.join(small(q), relation.predicate()).groupBy("qid").agg(F.count(F.lit(1)).alias("valid"))
    return queries.select("qid").join(pairs, "qid", "left").select("qid", F.coalesce("valid", F.lit(0)).alias("valid")).withColumn("sigma", F.col("valid") / F.lit(max(n, 1)))


def graph_stats(index: DataFrame) -> DataFrame:
    """kind, edges, mean_width (of labels, in thresholds), and the mean, median and largest degree of any kind."""
    e = index.select(F.explode(F.arrays_zip("l", "r", "kind")).alias("e")).select("e.*")
    degree = index.agg(F.avg(F.size("dst")).alias("mean_degree"), F.percentile_approx(F.size("dst"), 0.5).alias("median_degree"), F.max(F.size("dst")).alias("max_degree"))
    return e.groupBy("kind").agg(F.count(F.lit(1)).alias("edges"), F.avg(F.col("r") - F.col("l") + 1).alias("mean_width")).join(F.broadcast(degree))  # one row
