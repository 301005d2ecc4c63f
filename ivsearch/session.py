"""Settings read from the session, and tables written to the shared folder."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster names for checkpoints; where none is set, one in the warehouse, which all executors share."""
    at = spark.conf.get("spark.checkpoint.dir", None)
    return at or f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/ivsearch-staged"


def materialize(df: DataFrame, name: str = "t") -> DataFrame:
    """df written to the shared folder and read back: cuts lineage and survives lost executors."""
    spark, path = df.sparkSession, f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def light_batches(spark: SparkSession) -> None:
    """Keeps the batches that Python workers get small from here on: a setting of the session that holds when the caller runs what an operator returns."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "2000")
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(16 << 20))


def small(df: DataFrame, rows: int = 20_000, bytes_a_value: int = 1024) -> DataFrame:
    """A broadcast hint where df is found to be small, by rows and, where it holds arrays, strings or structs, by what these weigh; a shuffled join beyond that."""
    of = {c: F.size(c) * 8 if t.startswith("array<") and "<" not in t[6:] else F.octet_length(c) if t in ("string", "binary") else F.length(F.to_json(F.struct(c))) for c, t in df.dtypes if t in ("string", "binary") or "<" in t}
    weight = sum((F.coalesce(w, F.lit(0)) for w in of.values()), F.lit(0))
    n, size = df.limit(rows + 1).agg(F.count(F.lit(1)), F.coalesce(F.sum(weight), F.lit(0))).first()
    return F.broadcast(df) if n <= rows and size <= rows * bytes_a_value else df


def number(df: DataFrame, order: list[str], name: str, partitions: int | None = None) -> DataFrame:
    """df with name: the row's place from 0 in the global order of the columns.

    Rows are dealt by ranges and numbered inside each; offsets come from one count a range. No window spans the whole table.
    """
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = materialize(df.repartitionByRange(n, *order).withColumn("_part", F.spark_partition_id()), "ranges")
    counts = dealt.groupBy("_part").agg(F.count(F.lit(1)).alias("_n"))
    first = counts.select("_part", (F.sum("_n").over(W.orderBy("_part")) - F.col("_n")).alias("_first"))  # a row for each range
    own = F.row_number().over(W.partitionBy("_part").orderBy(*order)) - 1
    return dealt.withColumn("_own", own).join(F.broadcast(first), "_part").withColumn(name, F.col("_first") + F.col("_own")).drop("_part", "_own", "_first")
