"""Interval files, payloads and result sinks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

INTERVALS = "oid bigint, s double, t double"


def load(spark: SparkSession, sf_dir: str, *names: str) -> dict[str, DataFrame]:
    return {n: spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in names}


def read_intervals(spark: SparkSession, path: str, kind: str = "csv", schema: str = INTERVALS) -> DataFrame:
    """Intervals from csv (with a header), json lines, orc or parquet; rows that a reader cannot parse have nulls, and accept() leaves them out."""
    reader = spark.read.schema(schema)
    return (reader.option("header", True) if kind == "csv" else reader).format(kind).load(path)


def write_intervals(intervals: DataFrame, path: str, kind: str = "csv") -> None:
    out = intervals.select("oid", "s", "t").write.mode("overwrite")
    (out.option("header", True) if kind == "csv" else out).format(kind).save(path)


def write_results(results: DataFrame, path: str, kind: str = "parquet") -> None:
    """Results or measures, replaced as a whole; maps become json text where the format has none."""
    maps = [c for c, t in results.dtypes if t.startswith("map")] if kind == "csv" else []
    results.withColumns({c: F.to_json(c) for c in maps}).write.mode("overwrite").format(kind).save(path)


def props(events: DataFrame) -> DataFrame:
    """events with k, the number in their json payload (null where it has none)."""
    return events.withColumn("k", F.from_json("props", "k bigint")["k"])


def page_text(html: str) -> Column:
    """The text of a page: tags become spaces, runs of white space one."""
    return F.trim(F.regexp_replace(F.regexp_replace(html, "<[^>]*>", " "), "[ \\t\\n\\r]+", " "))


def host(url: str) -> Column:
    return F.call_function("try_parse_url", F.col(url), F.lit("HOST"))


def month(at: str) -> tuple[Column, Column]:
    """The first and the last microsecond of a timestamp's month, as numbers on the axis."""
    first = F.date_trunc("month", F.col(at).cast("timestamp"))
    return F.unix_micros(first).cast("double"), (F.unix_micros(F.add_months(first, 1).cast("timestamp")) - 1).cast("double")


def sample(df: DataFrame, key: str, one_in: int, seed: str = "sample") -> DataFrame:
    """About one row in so many, the same in every run and engine."""
    h = F.md5(F.concat(F.lit(f"{seed}:"), F.col(key).cast("string")))
    return df.where(F.conv(F.substring(h, 1, 8), 16, 10).cast("long") % one_in == 0)
