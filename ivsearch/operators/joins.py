"""Joins that Spark lacks: as-of, nearest neighbours in blocks, and nearest among earlier objects."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..session import light_batches, small

OUT = "qid long, oid long, dist double"


def cell_of(x, cuts: list[float]):
    """The number of cuts at or below x: a binary search in a literal array, so the expression stays small whatever the number of cuts."""
    if not cuts:
        return F.lit(0)
    at = F.lit([float(c) for c in cuts])
    steps = max(1, len(cuts).bit_length())
    half = [1 << i for i in range(steps - 1, -1, -1)]
    probe = lambda p, h: F.when((p + h <= len(cuts)) & (F.coalesce(F.get(at, p + h - 1), F.lit(float("inf"))) <= x), p + h).otherwise(p)
    return F.aggregate(F.lit(half), F.lit(0), probe)


def cuts_of(df: DataFrame, column: str, cells: int) -> list[float]:
    return sorted(set(df.approxQuantile(column, [i / cells for i in range(1, cells)], 0.001))) if cells > 1 else []


def asof(left: DataFrame, right: DataFrame, at: str, val: str, direction: str = "forward", cells: int = 64) -> DataFrame:
    """left with found: the least val of right at or above left's at (`forward`), or the greatest at or below (`backward`); null if there is none.

    Both sides are dealt to ranges of val and merged in one window inside each; what a range cannot answer comes from the nearest
    range that has a value, by one row a range. No pair of rows is made, and nothing is broadcast but those rows. Null at finds nothing.
    """
    s = 1 if direction == "forward" else -1
    key, vals = F.col(at).cast("double") * s, right.select((F.col(val).cast("double") * s).alias("v")).where("v is not null").distinct()
    cuts = cuts_of(vals, "v", cells)
    vals = vals.withColumn("cell", cell_of(F.col("v"), cuts))
    later = W.orderBy(F.col("cell").desc()).rowsBetween(W.unboundedPreceding, -1)
    ranges = small_frame(left, len(cuts) + 1).join(vals.groupBy("cell").agg(F.min("v").alias("least")), "cell", "left")
    ranges = ranges.select(F.col("cell").alias("_cell"), F.min("least").over(later).alias("_next"))  # a row for each cell
    named = left.withColumns({"_v": key, "_cell_": cell_of(key, cuts)}).where(F.col("_v").isNotNull())
    both = named.withColumn("_right", F.lit(None).cast("double")).unionByName(vals.select(F.col("v").alias("_v"), F.col("cell").alias("_cell_"), F.col("v").alias("_right")), allowMissingColumns=True).withColumn("_is", F.col("_right").isNull())
    ahead = W.partitionBy("_cell_").orderBy("_v").rangeBetween(W.currentRow, W.unboundedFollowing)
    met = both.withColumn("_own", F.min("_right").over(ahead)).where("_is").join(F.broadcast(ranges), F.col("_cell_") == F.col("_cell"), "left")
    found = met.select(*left.columns, (F.coalesce("_own", "_next") * s).alias("found"))
    return found.unionByName(left.where(key.isNull()).withColumn("found", F.lit(None).cast("double")))


def small_frame(df: DataFrame, n: int) -> DataFrame:
    return df.sparkSession.range(n).select(F.col("id").cast("int").alias("cell"))


def _matrix(column) -> np.ndarray:
    flat = (column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column)
    return flat.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(flat), -1) if len(flat) else np.zeros((0, 0))


def measured(q: np.ndarray, v: np.ndarray, rows: np.ndarray, cols: np.ndarray) -> np.ndarray:
    """Distances of the pairs (q[rows], v[cols]), summed component by component in their order: the doubles that SQL engines get, so that ties are ties there too."""
    total, qt, vt = np.zeros(len(rows)), np.ascontiguousarray(q.T), np.ascontiguousarray(v.T)
    for a, b in zip(qt, vt):
        e = b[cols] - a[rows]
        total += e * e
    return np.sqrt(total)


def nearest_in(q: np.ndarray, v: np.ndarray, oid: np.ndarray, k, allowed=None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of q, row of v, distance) of the k nearest v of each q (k: one for all or one each), ties to smaller oids: chosen by a matrix product with some to spare, measured anew by differences."""
    most = int(np.max(k)) if len(q) else 0
    if not len(q) or not len(v) or most < 1:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    sq, own = (v * v).sum(1), (q * q).sum(1)
    d = q @ v.T
    d *= -2
    d += sq
    d += own[:, None]
    finite = np.isfinite(d)
    if allowed is not None:
        finite &= allowed
    np.putmask(d, ~finite, np.inf)
    edge = np.partition(d, most - 1, axis=1)[:, most - 1] if most < len(v) else np.full(len(q), np.inf)
    spare = 1e-9 * (1 + np.abs(edge)) + 1e-12 * own  # all that rounding could bring in
    finite &= d <= (edge + spare)[:, None]
    return nearest_of(q, v, oid, k, *np.nonzero(finite))


def nearest_of(q: np.ndarray, v: np.ndarray, oid: np.ndarray, k, rows: np.ndarray, cols: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of q, row of v, distance) of the k nearest of the pairs (rows, cols) of each q, ties to smaller oids."""
    dist = measured(q, v, rows, cols)
    order = np.lexsort((oid[cols], dist, rows))
    rows, cols, dist = rows[order], cols[order], dist[order]
    best = np.arange(len(rows)) - np.searchsorted(rows, rows) < np.broadcast_to(k, len(q))[rows]
    return rows[best], cols[best], dist[best]


def query_blocks(queries: DataFrame, block: int = 16_384) -> list[DataFrame]:
    """queries in parts of about block rows, by a hash of qid; each is small enough to be broadcast."""
    n = max(1, -(-queries.count() // block))
    return [queries] if n == 1 else [queries.where(F.pmod(F.xxhash64(F.lit(9), "qid"), F.lit(n)) == i) for i in range(n)]


def by_width(column) -> list[tuple[np.ndarray, np.ndarray]]:
    """(places, matrix) of a column of vectors for each of their lengths; nulls and empty ones are in none."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    width = column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
    places = [np.flatnonzero(width == w) for w in np.unique(width[width > 0])]
    return [(p, _matrix(column if len(p) == len(column) else column.take(pa.array(p)))) for p in places]


def knn_join(queries: DataFrame, objects: DataFrame, k: int, valid=None, extra: tuple[str, ...] = (), block: int = 16_384, near=None, by: str | None = None) -> DataFrame:
    """qid, oid, dist: for each task of objects (oid, vec, extra) the k nearest of each query (qid, qvec, extra), for a merge by rank.

    Queries go to the tasks in broadcast blocks; a task meets a block by one matrix product a batch, and keeps k of each query and batch.
    valid(query arrays, object arrays) is a mask of allowed pairs over the extra columns. near(query arrays, object arrays) names the objects that
    some of a few queries, taken in the order of by, can reach: only their vectors are looked at. Vectors of another length never meet.
    """
    spark = objects.sparkSession
    light_batches(spark)
    parts, step = [], 256 if near is None else 128  # so many distances to a batch stay in the processor's cache
    for some in query_blocks(queries, block):
        sent = spark.sparkContext.broadcast(some.select("qid", "qvec", *[c for c in extra if c in some.columns]).toArrow())

        def run(batches, sent=sent):
            t = sent.value
            ids, asked = t.column("qid").to_numpy(), {c: t.column(c).to_numpy() for c in t.column_names if c in extra}
            order = np.arange(len(ids)) if by is None else np.argsort(asked[by], kind="stable")
            sets = {}
            for places, q in by_width(t.column("qvec").combine_chunks().take(pa.array(order)) if len(ids) else pa.array([], pa.list_(pa.float64()))):
                own = order[places]
                sets[q.shape[1]] = q, ids[own], {c: x[own] for c, x in asked.items()}
            for b in batches:
                for places, v in by_width(b.column("vec")):
                    if v.shape[1] not in sets:
                        continue
                    q, qid, qe = sets[v.shape[1]]
                    oid = b.column("oid").to_numpy()[places]
                    oe = {c: b.column(c).to_numpy(zero_copy_only=False)[places] for c in b.schema.names if c in extra}
                    for at in range(0, len(qid), step):
                        cut = slice(at, at + step)
                        mine = {c: x[cut] for c, x in qe.items()}
                        met = slice(None) if near is None else near(mine, oe)
                        ok = valid(mine, {c: x[met] for c, x in oe.items()}) if valid else None
                        rows, cols, dist = nearest_in(q[cut], v[met], oid[met], k, ok)
                        yield pa.RecordBatch.from_arrays([pa.array(qid[cut][rows], pa.int64()), pa.array(oid[met][cols].astype(np.int64)), pa.array(dist)], ["qid", "oid", "dist"])

        parts.append(objects.select("oid", "vec", *[c for c in extra if c in objects.columns]).mapInArrow(run, OUT))
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out


def prefix_knn(ordered: DataFrame, z: int, block: int = 2048) -> DataFrame:
    """qid (an object's oid), rank, oid, dist: the z nearest of the objects before it, for objects (ord from 0, oid, vec).

    Blocks of the order meet as pairs (earlier or same, later), one task group each; a pair keeps z for each later object. The work is that of
    all pairs, in matrix products, and what is shuffled is each block once for every later one: for objects of one shard, not of a table.
    """
    b = ordered.withColumn("blk", F.floor(F.col("ord") / block).cast("int"))
    top = b.agg(F.coalesce(F.max("blk"), F.lit(-1))).first()[0]
    late = b.withColumn("early", F.explode(F.sequence(F.lit(0), F.col("blk")))).select("early", F.col("blk").alias("late"), "ord", "oid", "vec")
    early = b.withColumn("late", F.explode(F.sequence(F.col("blk"), F.lit(max(top, 0))))).select(F.col("blk").alias("from_blk"), F.col("late").alias("to_blk"), F.col("ord").alias("at"), F.col("oid").alias("id"), F.col("vec").alias("v"))

    def run(key, x, y):
        q, v = _matrix(x.column("vec")), _matrix(y.column("v"))
        qo, vo = x.column("ord").to_numpy(), y.column("at").to_numpy()
        if not len(q) or not len(v):
            return pa.table({"qid": pa.array([], pa.int64()), "oid": pa.array([], pa.int64()), "dist": pa.array([], pa.float64())})
        oid = y.column("id").to_numpy()
        rows, cols, dist = nearest_in(q, v, oid, z, vo[None] < qo[:, None])
        return pa.table({"qid": pa.array(x.column("oid").to_numpy()[rows], pa.int64()), "oid": pa.array(oid[cols].astype(np.int64)), "dist": pa.array(dist)})

    found = late.groupBy("early", "late").cogroup(early.groupBy("from_blk", "to_blk")).applyInArrow(run, OUT)
    w = W.partitionBy("qid").orderBy("dist", "oid")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= z).select("qid", "rank", "oid", "dist")


def semi(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    return left.join(small(right.select(*on).distinct()), on, "left_semi")


def anti(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    return left.join(small(right.select(*on).distinct()), on, "left_anti")
