"""Checks of the index's structural claims."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .index import edges


def broken_labels(index: DataFrame) -> DataFrame:
    """Edges whose label lets in a state in which one end is not valid: there must be none."""
    ends = index.select("shard", "ord", "xr", "yr")
    e = edges(index)
    a = ends.select("shard", F.col("ord").alias("src"), F.col("xr").alias("xa"), F.col("yr").alias("ya"))
    b = ends.select("shard", F.col("ord").alias("dst"), F.col("xr").alias("xb"), F.col("yr").alias("yb"))
    return e.join(a, ["shard", "src"]).join(b, ["shard", "dst"]).where((F.col("l") > F.col("r")) | (F.col("r") > F.least("xa", "xb")) | (F.col("b") < F.greatest("ya", "yb")))


def active(index: DataFrame, a: int, c: int) -> DataFrame:
    """The distinct edges alive in a state of ranks."""
    return edges(index).where((F.col("l") <= a) & (F.col("r") >= a) & (F.col("b") <= c)).select("shard", "src", "dst").distinct()


def active_counts(index: DataFrame, states: DataFrame) -> DataFrame:
    """a, c, edges: distinct edges alive in each of the stated states."""
    s = states.select(F.col("a").alias("_a"), F.col("c").alias("_c"))
    hit = edges(index).join(F.broadcast(s), (F.col("l") <= F.col("_a")) & (F.col("r") >= F.col("_a")) & (F.col("b") <= F.col("_c")))
    return hit.select("_a", "_c", "shard", "src", "dst").distinct().groupBy(F.col("_a").alias("a"), F.col("_c").alias("c")).agg(F.count(F.lit(1)).alias("edges"))


def unconnected(index: DataFrame, a: int, c: int) -> int:
    """How many components the active graph of a state has beyond one a shard; labels spread from edge to edge, one shuffle a round."""
    from ..session import materialize

    nodes = index.where((F.col("xr") >= a) & (F.col("yr") <= c)).select("shard", F.col("ord").alias("node"), F.col("ord").alias("label"))
    e, last = materialize(active(index, a, c), "active"), None
    while True:
        near = e.join(nodes.withColumnRenamed("node", "src"), ["shard", "src"]).groupBy("shard", F.col("dst").alias("node")).agg(F.min("label").alias("m"))
        nodes = materialize(nodes.join(near, ["shard", "node"], "left").select("shard", "node", F.least("label", F.coalesce("m", "label")).alias("label")), "labels")
        total = nodes.agg(F.sum("label")).first()[0]
        if total == last:
            break
        last = total
    n, shards = nodes.agg(F.count_distinct("shard", "label"), F.count_distinct("shard")).first()
    return n - shards
