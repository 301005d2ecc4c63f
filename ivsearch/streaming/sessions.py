"""Intervals from event streams, and searches over streams."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.relations import Relation
from ..operators import index as idx


def sessions(events: DataFrame, gap: str = "6 hours", delay: str | None = None) -> DataFrame:
    """user_id, s, t, n: a user's events with gaps under gap; with delay a stream's watermark, after which later events of a session are dropped."""
    at = events.withColumn("ts", F.col("ts").cast("timestamp"))
    at = at.withWatermark("ts", delay) if delay else at
    by = at.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.min("ts").alias("s"), F.max("ts").alias("t"), F.count(F.lit(1)).alias("n"))
    return by.select("user_id", "s", "t", "n")


def fixed_intervals(events: DataFrame, size: str, slide: str | None = None, delay: str | None = None) -> DataFrame:
    """start, end, n: events of tumbling, or with slide of sliding, windows."""
    at = events.withColumn("ts", F.col("ts").cast("timestamp"))
    at = at.withWatermark("ts", delay) if delay else at
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return at.groupBy(w.alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def search_stream(queries: DataFrame, index: DataFrame, relation: Relation, sink: Callable[[DataFrame, int], None], **how):
    """A started streaming query that answers each micro-batch of queries from a snapshot of the index."""
    return queries.writeStream.foreachBatch(lambda batch, n: sink(idx.search(index, batch, relation, **how), n)).start()
