"""Axis coordinates of objects and queries, thresholds, canonical states."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.joins import asof
from ..session import materialize, number, small
from .relations import AxisPlan


def to_axis(df: DataFrame, column: str) -> Column:
    """Numbers as double; dates and timestamps as microseconds, which doubles hold exactly for the next two centuries."""
    kind = df.schema[column].dataType
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType, T.DateType)):
        return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', cast(`{column}` as timestamp_ntz))").cast("double")
    return F.col(column).cast("double")


def on_axis(df: DataFrame, *ends: str) -> DataFrame:
    """df with its endpoints as doubles: dates, timestamps and decimals may stand in it."""
    return df.withColumns({c: to_axis(df, c) for c in ends if not isinstance(df.schema[c].dataType, T.DoubleType)})


def accept(objects: DataFrame, dim: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(valid, rejected) objects, endpoints as doubles: an oid, s and t known and finite, s <= t, and a vector of finite components, dim of them if that is given."""
    o = on_axis(objects, "s", "t")
    finite = lambda x: ~F.isnan(x) & (F.abs(x) < float("inf"))
    v = F.col("vec").isNotNull() & F.forall("vec", lambda x: x.isNotNull() & finite(x))
    ok = F.col("oid").isNotNull() & v & finite(F.col("s")) & finite(F.col("t")) & (F.col("s") <= F.col("t"))
    ok = F.coalesce(ok & (F.size("vec") == dim) if dim is not None else ok, F.lit(False))
    return o.where(ok), o.where(~ok)


def whole(objects: DataFrame) -> DataFrame:
    """The valid objects of one dimension, the most frequent (the smaller of equally frequent ones), one an oid: of rows that repeat an oid, the smallest by s, t and vector."""
    good, _ = accept(objects)
    most = good.groupBy(F.size("vec").alias("n")).agg(F.count(F.lit(1)).alias("rows")).orderBy(F.col("rows").desc(), "n").first()
    if most is None:
        return good
    good = good.where(F.size("vec") == most.n)
    again = small(materialize(good.groupBy("oid").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("oid"), "again"))
    if again.isEmpty():
        return good
    rest = ["s", "t", "vec", *[c for c in good.columns if c not in ("oid", "s", "t", "vec")]]
    one = good.join(again, "oid", "left_semi").groupBy("oid").agg(F.min_by(F.struct(*rest), F.struct("s", "t", "vec")).alias("o")).select("oid", "o.*").select(*good.columns)
    return good.join(again, "oid", "left_anti").select(*good.columns).union(one)


def attach(objects: DataFrame, plan: AxisPlan) -> DataFrame:
    x, y = plan.object_axes()
    return on_axis(objects, "s", "t").withColumns({"x": x, "y": y})


def attach_queries(queries: DataFrame, plan: AxisPlan) -> DataFrame:
    x, y = plan.query_axes()
    return on_axis(queries, "sq", "tq").withColumns({"xq": x, "yq": y})


def thresholds(objects: DataFrame, axis: str) -> DataFrame:
    """val, rank from 0: the distinct coordinates of an axis in order."""
    return number(objects.select(F.col(axis).alias("val")).distinct(), ["val"], "rank").select("val", F.col("rank").cast("long"))


def snap(queries: DataFrame, objects: DataFrame) -> DataFrame:
    """queries with a (least object X at or above xq) and c (greatest object Y at or below yq); null: nothing is valid.

    Two as-of joins with the distinct coordinates: sorted merges inside ranges, no pair of a query and an object.
    """
    up = asof(queries, objects.select("x"), "xq", "x", "forward").withColumnRenamed("found", "a")
    return asof(up, objects.select("y"), "yq", "y", "backward").withColumnRenamed("found", "c")


def entry_table(objects: DataFrame) -> DataFrame:
    """Objects at which the largest X so far, in the order of (y, oid), grows: the last with y <= c is valid in state (a, c) or none is.

    Two levels: objects are dealt to ranges of the order; the largest X of all earlier ranges, one row a range, starts the running maximum inside each.
    """
    n = int(objects.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = materialize(objects.select("oid", "x", "y").repartitionByRange(n, "y", "oid").withColumn("_part", F.spark_partition_id()), "ranges")
    earlier = W.orderBy("_part").rowsBetween(W.unboundedPreceding, -1)
    tops = dealt.groupBy("_part").agg(F.max("x").alias("_top")).select("_part", F.max("_top").over(earlier).alias("_top"))  # a row for each range
    own = F.max("x").over(W.partitionBy("_part").orderBy("y", "oid").rowsBetween(W.unboundedPreceding, -1))
    before = dealt.withColumn("_own", own).join(F.broadcast(tops), "_part").withColumn("_before", F.greatest("_own", "_top"))
    return before.where(F.col("_before").isNull() | (F.col("x") > F.col("_before"))).select("oid", "x", "y")
