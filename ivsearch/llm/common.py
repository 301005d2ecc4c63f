"""Helpers shared by the training-data operators."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Words are runs of anything but these: space and U+0009 to U+000D.
WORD = r"[^\x20\x09-\x0D]+"
BLANKS = " \t\n\x0b\x0c\r"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster names for checkpoints; where none is set, one in the warehouse, which all executors share."""
    at = spark.conf.get("spark.checkpoint.dir", None)
    return at or f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/ivsearch-staged"


#: Has Spark delete a query's shuffle files when the query ends, not when the driver collects garbage.
CLEANUP = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true"}
#: Keeps batches of whole texts that Python workers get small.
BATCHES = {"spark.sql.execution.arrow.maxRecordsPerBatch": "500", "spark.sql.execution.arrow.maxBytesPerBatch": str(16 << 20)}


def light_batches(spark: SparkSession) -> None:
    """Keeps the batches that Python workers get small from here on: a setting of the session that holds when the caller runs what an operator returns."""
    for k, v in BATCHES.items():
        spark.conf.set(k, v)


def stage(df: DataFrame, name: str = "t") -> DataFrame:
    """Writes df as a table in the shared folder and reads it back: lineage ends here, and lost executors cost no recomputation."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    settings = CLEANUP | BATCHES
    before = {k: spark.conf.get(k, None) for k in settings}
    for k, v in settings.items():
        spark.conf.set(k, v)
    try:
        df.write.parquet(path)
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    return spark.read.schema(df.schema).parquet(path)


def unstage(df: DataFrame) -> None:
    """Deletes what stage() wrote, when nothing reads it any more."""
    spark = df.sparkSession
    for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        p = spark._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def n_words(text: str | Column) -> Column:
    """Words of a text; null has none."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def small(df: DataFrame, rows: int = 20_000) -> DataFrame:
    """df marked for broadcast if it is found to have few rows; as it is, for a shuffled join, beyond that."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def hidden(df: DataFrame, drop: list[str] | tuple = ()) -> tuple[DataFrame, dict[str, str]]:
    """df without the columns in drop and with its columns named u0, u1, ..., and their names by the old ones: no column of a caller can then clash with a name that an operator uses."""
    names = {c: f"u{i}" for i, c in enumerate(c for c in df.columns if c not in drop)}
    return df.select(*[F.col(f"`{c}`").alias(u) for c, u in names.items()]), names


def shown(names: dict[str, str], **other: Column) -> list[Column]:
    """The columns of hidden() under their own names; other takes the place of a column."""
    return [other[c].alias(c) if c in other else F.col(u).alias(c) for c, u in names.items()]


def excerpt(text: str, chars: int, piece: int = 256) -> Column:
    """The text, or where it has more than so many characters, as many in pieces from all over it, evenly spaced."""
    n, t = max(1, chars // piece), F.col(text)
    step = (F.length(t) - piece) / max(1, n - 1)
    spread = F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.substring(t, F.floor(i * step).cast("int") + 1, F.lit(piece)))
    return F.when(F.length(t) <= chars, t).otherwise(F.array_join(spread, " "))


def held(doc_id: str | Column, mod: int) -> Column:
    """crc32 of the id's decimal text, modulo mod."""
    return F.crc32((F.col(doc_id) if isinstance(doc_id, str) else doc_id).cast("string").cast("binary")) % mod


def lowest(rows: DataFrame, n: int) -> DataFrame:
    """The n rows with the smallest h (a 64-bit hash), ties by the other columns. Only a slice of hashes that should hold a few times n is sorted, so what tasks send does not grow with the rows."""
    total = rows.count()
    share = (4 * n + 100) / max(total, 1)
    if share < 1:
        part = rows.where(F.col("h") < -(2**63) + int(share * 2**64))
        rows = part if part.count() >= n else rows
    return rows.orderBy("h", *[c for c in rows.columns if c != "h"]).limit(n)
