"""The engine from SQL: functions, a bounded top-k aggregate, a table function, and the rewriting of one shape of query."""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..functions import coords, relations
from ..operators import exact, index, stats

#: Names of functions in SQL and their bodies, which Spark puts in place of the calls.
FUNCTIONS = {
    "iv_l2(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>)": "DOUBLE RETURN sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (p, q) -> p + q))",
    "iv_contained(s DOUBLE, t DOUBLE, a DOUBLE, b DOUBLE)": "BOOLEAN RETURN s >= a AND t <= b",
    "iv_overlaps(s DOUBLE, t DOUBLE, a DOUBLE, b DOUBLE)": "BOOLEAN RETURN t >= a AND s <= b",
    "iv_covers(s DOUBLE, t DOUBLE, a DOUBLE, b DOUBLE)": "BOOLEAN RETURN t >= b AND s <= a",
    "iv_after(s DOUBLE, t DOUBLE, a DOUBLE, b DOUBLE)": "BOOLEAN RETURN s >= a AND t >= b",
    "iv_before(s DOUBLE, t DOUBLE, a DOUBLE, b DOUBLE)": "BOOLEAN RETURN s <= a AND t <= b",
}


def register(spark: SparkSession) -> None:
    for head, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURNS {body}")


def topk_by(rows: DataFrame, key: str, by: str, value: str, k: int, parts: int = 64) -> DataFrame:
    """key, rank, value, by: the k smallest of each key by (by, value). Two levels of a bounded aggregate: a key's rows are first dealt to parts by a hash, so a key of any size never meets in one task but as k rows a part."""
    pair = F.struct(F.col(by).alias("d"), F.col(value).alias("v"))
    least = lambda c: F.slice(F.array_sort(c), 1, k)
    dealt = rows.withColumn("_part", F.pmod(F.xxhash64(value), F.lit(parts)))
    w = F.row_number().over(W.partitionBy(key, "_part").orderBy(by, value))
    part = dealt.withColumn("_r", w).where(F.col("_r") <= k).groupBy(key).agg(least(F.collect_list(pair)).alias("top"))
    return part.select(key, F.posexplode("top").alias("rank", "x")).select(key, (F.col("rank") + 1).cast("long").alias("rank"), F.col("x.v").alias(value), F.col("x.d").alias(by))


def interval_knn(shards: DataFrame, relation: relations.Relation, name: str = "interval_knn") -> None:
    """Registers a table function: name(qvec, sq, tq, k, ef) gives (oid, dist), nearest first, from packed shards.

    Each call opens the shards that the query's corner meets; they are broadcast, so this form is for indexes of up to 64 MB. Larger ones are searched by index.search().
    """
    spark = shards.sparkSession
    size = shards.agg(F.coalesce(F.sum(F.octet_length("blob")), F.lit(0))).first()[0]
    if size > 64 << 20:
        raise ValueError(f"{size} bytes of shards are too many for a table function; use index.search()")
    held = spark.sparkContext.broadcast([(r.x1, r.y0, bytes(r.blob)) for r in shards.select("x1", "y0", "blob").collect()])
    plan = relation.plan()
    signs, ends = plan.signs, (plan.x.query, plan.y.query)

    @udtf(returnType="oid: bigint, dist: double")
    class Knn:
        def __init__(self):
            self.open: dict = {}

        def eval(self, qvec, sq: float, tq: float, k: int, ef: int):
            import numpy as np

            at = {"sq": sq, "tq": tq}
            if qvec is None or sq is None or tq is None:
                return
            xq, yq = (s * at[e] for s, e in zip(signs, ends))
            best = []
            for i, (x1, y0, blob) in enumerate(held.value):
                if x1 >= xq and y0 <= yq:
                    shard = self.open.setdefault(i, None) or index.Shard(blob)
                    self.open[i] = shard
                    rows, dist, _ = shard.find(np.array(qvec, np.float64), xq, yq, k, ef, "walk", 0, k)
                    best += zip(dist.tolist(), shard.oid[rows].tolist())
            for d, oid in sorted(best)[:k]:
                yield oid, d

    spark.udtf.register(name, Knn)


def interval_knn_blocks(spark: SparkSession, relation: relations.Relation, name: str = "interval_knn_blocks") -> None:
    """Registers a table function for indexes of any size: name(blob, qids, qvecs, sqs, tqs, k, ef) gives (qid, oid, dist), the k nearest of one packed shard for each of a block of queries. Joined laterally to a table of shards and one of blocks, it leaves the merge over shards to SQL."""
    plan = relation.plan()
    signs, ends = plan.signs, (plan.x.query, plan.y.query)

    @udtf(returnType="qid: bigint, oid: bigint, dist: double")
    class Knn:
        def eval(self, blob: bytes, qids, qvecs, sqs, tqs, k: int, ef: int):
            import numpy as np

            if blob is None or not qids:
                return
            shard = index.Shard(bytes(blob))
            at = {"sq": sqs, "tq": tqs}
            some = [i for i, v in enumerate(qvecs) if v is not None and len(v) == shard.v.shape[1] and sqs[i] is not None and tqs[i] is not None]
            for to in range(0, len(some), 512):
                own = some[to : to + 512]
                q = np.array([qvecs[i] for i in own], np.float64)
                xq, yq = (s * np.array([at[e][i] for i in own], np.float64) for s, e in zip(signs, ends))
                if ef >= len(shard.oid):
                    rows, ids, dist, _ = shard.find_many(q, xq, yq, np.full(len(own), k), "walk", 0)
                    found = zip(rows.tolist(), shard.oid[ids].tolist(), dist.tolist())
                else:
                    each = [shard.find(q[i], xq[i], yq[i], k, ef, "walk", 0, k) for i in range(len(own))]
                    found = ((i, o, d) for i, e in enumerate(each) for o, d in zip(shard.oid[e[0]].tolist(), e[1].tolist()))
                for i, oid, d in found:
                    yield qids[own[i]], oid, d

    spark.udtf.register(name, Knn)


_SHAPE = re.compile(
    r"\s*SELECT\s+oid\s+FROM\s+\(\s*SELECT\s+oid,\s*iv_l2\(vec,\s*:q\)\s+AS\s+dist\s+FROM\s+(\w+)\s+WHERE\s+iv_(contained|overlaps|covers|after|before)\(s,\s*t,\s*:a,\s*:b\)\s*\)"
    r"\s+ORDER\s+BY\s+dist(?:,\s*oid)?\s+LIMIT\s+:k\s*;?\s*", re.I)  # fmt: skip


def sql(spark: SparkSession, text: str, args: dict, indexes: dict | None = None, ef: int = 128) -> DataFrame:
    """Runs text. The one shape SELECT oid FROM (SELECT oid, iv_l2(vec, :q) AS dist FROM table WHERE iv_relation(s, t, :a, :b)) ORDER BY dist LIMIT :k is answered from indexes[(table, relation)], packed, if there is one; all else runs as it is written, exactly."""
    m = _SHAPE.fullmatch(text)
    if m and indexes and (key := (m[1].lower(), m[2].lower())) in indexes:
        q = spark.createDataFrame([(0, [float(x) for x in args["q"]], float(args["a"]), float(args["b"]), int(args["k"]))], "qid long, qvec array<double>, sq double, tq double, k int")
        return index.search(indexes[key], q, relations.ALL[key[1]], ef).orderBy("rank").select("oid")
    vector = lambda v: F.array(*[F.lit(float(x)) for x in v]) if isinstance(v, (list, tuple)) else v
    return spark.sql(text, args={k: vector(v) for k, v in args.items()})


def planned(objects: DataFrame, shards: DataFrame, queries: DataFrame, relation: relations.Relation, scan_below: int = 64, ef: int = 64, cells: int = 64) -> tuple[DataFrame, DataFrame]:
    """(results, choice): a grid of counts bounds each query's valid set; queries with few valid objects are scanned exactly, those with none get nothing, the others walk the graph."""
    plan = relation.plan()
    counts, frame = stats.grid(coords.attach(objects, plan), cells)
    how = stats.choose(stats.bounds(coords.attach_queries(queries, plan), counts, frame, cells), scan_below)
    mine = lambda name: queries.join(how.where(F.col("how") == name).select("qid"), "qid", "left_semi")
    return exact.filtered_knn(objects, mine("scan"), relation).union(index.search(shards, mine("walk"), relation, ef)), how


def outside(text_terms: list[str], objects: DataFrame, queries: DataFrame, predicate: Column | None = None) -> DataFrame:
    """Search by any predicate: terms in the closed class compile to a relation; for others the exact filter on predicate is offered."""
    try:
        return exact.filtered_knn(objects, queries, relations.custom(*text_terms))
    except relations.UnsupportedRelation:
        if predicate is None:
            raise
        return exact.by_predicate(objects, queries, predicate)
