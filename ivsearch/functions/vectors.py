"""Distances and vectors as built-in expressions, in double precision."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _fold(xs: Column) -> Column:
    return F.aggregate(xs, F.lit(0.0), lambda a, b: a + b)


def dot(a, b) -> Column:
    return _fold(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")))


def l2sq(a, b) -> Column:
    return _fold(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))))


def l2(a, b) -> Column:
    return F.sqrt(l2sq(a, b))


def norm(a) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a, b) -> Column:
    return dot(a, b) / F.nullif(norm(a) * norm(b), F.lit(0.0))


def normalise(a) -> Column:
    return F.transform(a, lambda x: x.cast("double") / norm(a))


def valid_vector(v, dim: int | None = None) -> Column:
    ok = F.col(v).isNotNull() & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x))
    return ok & (F.size(v) == dim) if dim else ok


def hash_text(df: DataFrame, key: str, text: str, d: int = 64) -> DataFrame:
    """key and vec: counts of the lower-cased words in d hashed cells, of length 1. One row per key; a text without words has no vector."""
    words = df.select(key, F.explode(F.split(F.lower(F.trim(text)), r"\s+")).alias("w")).where("w <> ''")
    cells = words.groupBy(key, (F.conv(F.substring(F.md5("w"), 1, 8), 16, 10).cast("long") % d).cast("int").alias("i")).agg(F.count(F.lit(1)).alias("n"))
    rows = cells.groupBy(key).agg(F.map_from_entries(F.collect_list(F.struct("i", "n"))).alias("m"))
    raw = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0)).cast("double"))
    return rows.withColumn("raw", raw).withColumn("len", norm(F.col("raw"))).select(key, F.transform("raw", lambda x: x / F.col("len")).alias("vec"))
