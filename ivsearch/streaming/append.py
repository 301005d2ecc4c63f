"""An index that grows by batches: objects in Y order are linked into open shards, late ones wait in a delta that is searched exactly."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.coords import attach, whole
from ..functions.relations import Relation
from ..operators import exact, index


class Appender:
    """Batches of objects (oid, vec, s, t), each written under its number, so that one delivered again replaces itself.

    Labels are open above in Y, so a shard whose objects all lie above those before it leaves earlier labels as they are: each batch's objects with a Y
    above the largest so far become packed shards of their own; those at or below it are late, and go to the delta. A search merges the shards' walks with an exact
    scan of the delta. compact() builds one index of everything.
    """

    def __init__(self, spark: SparkSession, relation: Relation, path: str, shard_rows: int = 4000, **how):
        self.spark, self.relation, self.path, self.shard_rows, self.how = spark, relation, path, shard_rows, how
        self.tops: dict[int, float] = {}

    def add(self, objects: DataFrame, batch: int) -> None:
        if batch in self.tops:  # what it wrote stands
            return
        top = max(self.tops.values(), default=float("-inf"))
        placed = attach(whole(objects), self.relation.plan())
        on_time, late = placed.where(F.col("y") > top), placed.where(F.col("y") <= top)
        late.select("oid", "vec", "s", "t").write.mode("overwrite").parquet(f"{self.path}/delta/batch={batch}")
        built = index.build(on_time.select("oid", "vec", "s", "t"), self.relation, shard_rows=self.shard_rows, **self.how)
        index.pack(built).write.mode("overwrite").parquet(f"{self.path}/shards/batch={batch}")
        reached = on_time.agg(F.max("y")).first()[0]
        self.tops[batch] = top if reached is None else reached

    def write_stream(self, objects: DataFrame):
        """A started streaming query that adds each micro-batch."""
        return objects.writeStream.option("checkpointLocation", f"{self.path}/progress").foreachBatch(self.add).start()

    def search(self, queries: DataFrame, ef: int = 64) -> DataFrame:
        shards = self.spark.read.parquet(f"{self.path}/shards").drop("batch")
        delta = self.spark.read.parquet(f"{self.path}/delta").drop("batch")
        found = index.search(shards, queries, self.relation, ef).select("qid", "oid", "dist").union(exact.filtered_knn(delta, queries, self.relation).select("qid", "oid", "dist"))
        return exact.top(found.join(queries.select("qid", "k"), "qid"))
