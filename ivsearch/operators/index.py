"""The state-labelled graph as a table: one row per object, with its labelled edges in arrays, sharded; and packed, one row per shard."""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.coords import attach, attach_queries, whole
from ..functions.relations import Relation, custom
from ..session import light_batches, materialize
from . import blobs, kernels
from .joins import _matrix, cell_of, cuts_of, measured, nearest_in, nearest_of, query_blocks

KIND = "shard int, ord int, oid long, vec array<double>, x double, y double, xr int, yr int, dst array<int>, l array<int>, r array<int>, b array<int>, kind array<int>, rounds int, uncovered int"
PACKED = "shard int, n long, x1 double, y0 double, blob binary"


def assign(objects: DataFrame, shard_rows: int, method: str = "hash") -> DataFrame:
    """objects with shard: `hash` by oid; `zone` by ranges of x, which lets selective queries skip shards. About shard_rows each."""
    shards = max(1, -(-objects.count() // shard_rows))
    if method == "zone" and shards > 1:
        return objects.withColumn("shard", cell_of(F.col("x"), cuts_of(objects, "x", shards)))
    return objects.withColumn("shard", F.pmod(F.xxhash64("oid"), F.lit(shards)).cast("int"))


def by_shard(df: DataFrame):
    """df grouped by shard, with shards dealt in turn to as many tasks as run at once: a hash of so few keys would leave some tasks with twice as many."""
    n = df.sparkSession.sparkContext.defaultParallelism
    return df.withColumn("_task", F.pmod(F.col("shard"), F.lit(n))).repartitionById(n, F.col("_task")).groupBy("shard", "_task")


def _arrays(t: pa.Table):
    v = _matrix(t.column("vec"))
    oid, x, y = (t.column(c).to_numpy() for c in ("oid", "x", "y"))
    order = np.lexsort((oid, y))
    v, oid, x, y = v[order], oid[order], x[order], y[order]
    return v, oid, x, y, np.unique(x, return_inverse=True)[1], np.unique(y, return_inverse=True)[1]


def build(objects: DataFrame, relation: Relation, m: int = 16, method: str = "practical", pool: int = 200, leap: str = "max", patch: str = "anchored", kp: int = 8, shard_rows: int = 4000, sharding: str = "hash", swap: bool = False, pool_by: str = "scan") -> DataFrame:
    """The index of objects (oid, vec, s, t) for one relation. method `exact` sweeps every threshold; `practical` reuses a pool, leaps and patches; `incremental` takes candidates from the graph so far.

    A shard is one task, and shards are independent. With exact sweeps and scanned pools an object's links depend on earlier objects' data alone, not on their edges.
    Endpoints may be numbers, decimals, dates or timestamps. Objects outside the model (no oid, null or infinite or NaN endpoints, s > t, broken vectors or of
    another length than most) are left out; of rows that repeat an oid one is taken.
    """
    placed = assign(attach(whole(objects), relation.plan(swap)), shard_rows, sharding).select("shard", "oid", "vec", "x", "y")

    def run(key, t):
        v, oid, x, y, xr, yr = _arrays(t)
        rows, rounds, open_ = kernels.build(v, oid, xr, yr, m, method, pool, leap, patch, kp, pool_by)
        return _rows(key[0].as_py(), v, oid, x, y, xr, yr, rows, rounds, open_)

    return by_shard(placed).applyInArrow(run, KIND)


def _rows(shard: int, v, oid, x, y, xr, yr, found, rounds: int = 0, open_: int = 0) -> pa.Table:
    """A shard as KIND: found holds edges (src, dst, l, r, b, kind), of which each object gets its own in their order."""
    n, e = len(oid), np.array(found, np.int32).reshape(-1, 6)
    e = e[np.argsort(e[:, 0], kind="stable")]
    ends = pa.array(np.searchsorted(e[:, 0], np.arange(n + 1)), pa.int32())
    lists = [pa.ListArray.from_arrays(ends, pa.array(np.ascontiguousarray(e[:, i]))) for i in range(1, 6)]
    vec = pa.ListArray.from_arrays(pa.array(np.arange(n + 1) * v.shape[1], pa.int32()), pa.array(np.ascontiguousarray(v).reshape(-1)))
    one = lambda z: pa.array([z] + [0] * (n - 1), pa.int32())
    cols = [pa.array([shard] * n, pa.int32()), pa.array(range(n), pa.int32()), pa.array(oid, pa.int64()), vec, pa.array(x), pa.array(y), pa.array(xr, pa.int32()), pa.array(yr, pa.int32()), *lists, one(rounds), one(open_)]
    return pa.Table.from_arrays(cols, names=[c.split()[0] for c in KIND.split(", ")])


def pack(index: DataFrame) -> DataFrame:
    """index with one row for each shard: its zone (largest x, smallest y) and its arrays, edges as one list with offsets. Done once, it saves every search the shuffle of the index."""
    def run(key, t):
        t = t.sort_by("ord")
        dst = t.column("dst").combine_chunks()
        ends = np.concatenate([[0], np.cumsum(pa.compute.fill_null(pa.compute.list_value_length(dst), 0).to_numpy())])
        flat = {c: t.column(c).combine_chunks().flatten().to_numpy() for c in ("dst", "l", "r", "b")}
        x, y = t.column("x").to_numpy(), t.column("y").to_numpy()
        blob = blobs.pack(oid=t.column("oid").to_numpy(), v=_matrix(t.column("vec")), x=x, y=y, ends=ends.astype(np.int64), **flat)
        return pa.Table.from_arrays([pa.array([key[0].as_py()], pa.int32()), pa.array([t.num_rows], pa.int64()), pa.array([x.max()]), pa.array([y.min()]), pa.array([blob], pa.binary())], names=[c.split()[0] for c in PACKED.split(", ")])

    return by_shard(index).applyInArrow(run, PACKED)


def edges(index: DataFrame) -> DataFrame:
    """shard, src, dst, l, r, b, kind, and the coordinates' ranks at both ends where asked by joins."""
    e = F.explode(F.arrays_zip("dst", "l", "r", "b", "kind")).alias("e")
    return index.select("shard", F.col("ord").alias("src"), e).select("shard", "src", "e.*")


class Shard:
    """A packed shard, opened: rows by (y, oid), ranks, entries, and edges by row."""

    def __init__(self, blob: bytes):
        a = blobs.unpack(blob)
        self.v, self.oid, self.x, self.y, self.ends = a["v"], a["oid"], a["x"], a["y"], a["ends"]
        self.edges = tuple(a[c] for c in ("dst", "l", "r", "b"))
        (self.ux, self.xr), (self.uy, self.yr) = (np.unique(z, return_inverse=True) for z in (self.x, self.y))
        self.tops = kernels.prefix_tops(self.xr)

    def __getitem__(self, u: int) -> tuple:
        at, to = self.ends[u], self.ends[u + 1]
        return tuple(e[at:to] for e in self.edges)

    def find(self, q, xq: float, yq: float, k: int, ef: int, mode: str, scan_below: int, fan: int) -> tuple[np.ndarray, np.ndarray, tuple]:
        """(rows, distances, costs) of up to k valid objects, nearest first."""
        a, c = int(np.searchsorted(self.ux, xq)), int(np.searchsorted(self.uy, yq, side="right")) - 1
        last = int(np.searchsorted(self.y, yq, side="right")) - 1  # rows up to here have y <= yq
        none = np.zeros(0, np.int64), np.zeros(0), (0, 0, 0)
        if a >= len(self.ux) or last < 0 or self.xr[self.tops[last]] < a:
            return none
        start = int(self.tops[last])
        valid = (self.xr >= a) & (self.yr <= c) if mode != "walk" or scan_below else None
        if scan_below and valid.sum() <= scan_below:
            ids, costs = np.flatnonzero(valid), (int(valid.sum()), 0, 0)
        elif mode == "walk":
            ids, _, costs = kernels.walk(self.v, self, q, a, c, start, max(ef, k))
        elif mode == "post":
            ids, _, costs = kernels.walk(self.v, self, q, a, c, 0, max(ef, k), labels=False)
            ids = [i for i in ids if valid[i]]
        elif mode == "dense":
            ids, _, costs = kernels.walk(self.v, self, q, a, c, start, max(ef, k), labels=False, admit=valid, fan=fan)
        else:
            ids, _, costs = kernels.walk(self.v, self, q, a, c, start, max(ef, k), labels=False, admit=valid, hop_through=True)
        ids = np.array(ids, np.int64)
        d = measured(q[None], self.v, np.zeros(len(ids), np.int64), ids)
        best = np.lexsort((self.oid[ids], d))[:k]
        return ids[best], d[best], costs

    def find_many(self, q: np.ndarray, xq: np.ndarray, yq: np.ndarray, k: np.ndarray, mode: str, scan_below: int, costs_too: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(row of q, row, distance, costs of each q, zeros where not asked for): what find() gives where the pool holds the whole shard. Its walk then ends only when every row within reach is expanded, in whatever order, so all queries walk at once, by levels."""
        a, last = np.searchsorted(self.ux, xq), np.searchsorted(self.y, yq, side="right") - 1
        c = np.searchsorted(self.uy, yq, side="right") - 1
        some = np.flatnonzero((a < len(self.ux)) & (last >= 0) & (self.xr[self.tops[last]] >= a))
        costs, a, c, start = np.zeros((len(q), 3), np.int64), a[some], c[some], self.tops[last[some]]
        valid = (self.xr[None] >= a[:, None]) & (self.yr[None] <= c[:, None]) if mode != "walk" or scan_below else None
        if mode == "walk":
            seen = kernels.reach(len(self.oid), self.ends, self.edges[0], start, self.edges[1:], a, c)
        else:
            seen = kernels.reach(len(self.oid), self.ends, self.edges[0], np.zeros_like(start) if mode == "post" else start)
        if costs_too:
            met = seen.sum(1)
            costs[some] = np.stack([met, met, seen @ np.diff(self.ends)], 1)
        if scan_below:
            few = valid.sum(1) <= scan_below
            seen[few] = valid[few]
            if costs_too:
                costs[some[few]] = np.stack([valid[few].sum(1), np.zeros(few.sum(), np.int64), np.zeros(few.sum(), np.int64)], 1)
        at, rows, dist = nearest_in(q[some], self.v, self.oid, k[some], seen if mode == "walk" else seen & valid)
        return some[at], rows, dist, costs

    def walk_many(self, q: np.ndarray, xq: np.ndarray, yq: np.ndarray, k: np.ndarray, ef: int, mode: str, scan_below: int, fan: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray] | None:
        """What find() gives each of the queries, in the form of find_many(), by walks side by side; None for mode `predicate`, which passes through rows that are no answers."""
        if mode not in ("walk", "post", "dense"):
            return None
        a, last = np.searchsorted(self.ux, xq), np.searchsorted(self.y, yq, side="right") - 1
        c = np.searchsorted(self.uy, yq, side="right") - 1
        some = np.flatnonzero((a < len(self.ux)) & (last >= 0) & (self.xr[self.tops[last]] >= a))
        costs, pairs = np.zeros((len(q), 3), np.int64), []
        valid = (self.xr[None] >= a[some, None]) & (self.yr[None] <= c[some, None]) if mode != "walk" or scan_below else None
        if scan_below:
            few = valid.sum(1) <= scan_below
            costs[some[few], 0] = valid[few].sum(1)
            of, rows = np.nonzero(valid[few])
            pairs.append((some[few][of], rows))
            some, valid = some[~few], valid[~few]
        for width in np.unique(np.maximum(ef, k[some])).tolist():  # a pool holds k at least
            own = np.maximum(ef, k[some]) == width
            at = some[own]
            start = np.zeros(len(at), np.int64) if mode == "post" else self.tops[last[at]]
            of, rows, costs[at] = kernels.walk_many(self.v, self.ends, self.edges[0], q[at], start, min(width, len(self.oid)), self.edges[1:] if mode == "walk" else None, a[at], c[at], valid[own] if mode == "dense" else None, fan if mode == "dense" else None)
            if mode == "post":
                ok = valid[own][of, rows]
                of, rows = of[ok], rows[ok]
            pairs.append((at[of], rows))
        of, rows = (np.concatenate([np.zeros(0, np.int64), *p]) for p in (zip(*pairs) if pairs else ((), ())))
        return *nearest_of(q, self.v, self.oid, k, of, rows), costs


FOUND = "qid long, oid long, dist double, evals long, hops long, tests long, k int"


def each_shard(packed: DataFrame, queries: DataFrame, answer, open_shard=Shard, many=None, block: int = 512, costs: bool = True) -> DataFrame:
    """FOUND rows: answer(shard, query vector, xq, yq, k) -> (rows, distances, costs) for each packed shard and each query whose corner meets its zone; a row without oid carries the costs.

    many, where given, answers a block of queries at once: (shard, vectors, xq, yq, k) -> (row of the block, rows, distances, costs of each), or None for a shard that it leaves to answer.
    Shards stay where they are; the stated queries (qid, qvec, xq, yq, k) go to them in broadcast blocks. A task merges its shards' answers and hands on k of each query and, with costs, one row of their sums.
    """
    spark = packed.sparkSession
    light_batches(spark)
    out = None
    for some in query_blocks(queries.where("qvec is not null and xq is not null and yq is not null").select("qid", "qvec", "xq", "yq", "k")):
        sent = spark.sparkContext.broadcast(some.toArrow())

        def run(batches, sent=sent):
            t = sent.value
            qid, xq, yq, k = (t.column(c).to_numpy() for c in ("qid", "xq", "yq", "k"))
            vectors = t.column("qvec").combine_chunks()
            width = vectors.value_lengths().to_numpy(zero_copy_only=False)
            names, types = [c.split()[0] for c in FOUND.split(", ")], {"long": pa.int64(), "double": pa.float64(), "int": pa.int32()}
            kinds = [types[c.split()[1]] for c in FOUND.split(", ")]
            held, waiting = [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)], []  # place of the query, oid, distance
            spent, asked = np.zeros((len(qid), 3), np.int64), np.zeros(len(qid), bool)

            def nearest():
                of, oid, d = (np.concatenate([h, *w]) for h, w in zip(held, zip(*waiting)))
                order = np.lexsort((oid, d, of))
                of, oid, d = of[order], oid[order], d[order]
                best = np.arange(len(of)) - np.searchsorted(of, of) < k[of]
                return [of[best], oid[best], d[best]]

            for b in batches:
                for r in b.to_pylist():
                    meet = np.flatnonzero((r["x1"] >= xq) & (r["y0"] <= yq))
                    if not len(meet):
                        continue
                    shard = open_shard(r["blob"])
                    meet = meet[width[meet] == shard.v.shape[1]]
                    for at in range(0, len(meet), block):
                        own = meet[at : at + block]
                        q = _matrix(vectors.take(pa.array(own)))
                        found = many(shard, q, xq[own], yq[own], k[own]) if many else None
                        if found is None:
                            each = [answer(shard, q[i], float(xq[j]), float(yq[j]), int(k[j])) for i, j in enumerate(own)]
                            at_, rows, dist = np.repeat(np.arange(len(own)), [len(e[0]) for e in each]), np.concatenate([e[0] for e in each]), np.concatenate([e[1] for e in each])
                            took = np.array([e[2] for e in each], np.int64).reshape(-1, 3)
                        else:
                            at_, rows, dist, took = found
                        waiting.append((own[at_], shard.oid[rows.astype(np.int64)], dist))
                        spent[own] += took
                        asked[own] = True
                        if sum(len(w[0]) for w in waiting) > 1_000_000:
                            held, waiting = nearest(), []
            if waiting:
                held, waiting = nearest(), []
            for at in range(0, len(held[0]), 100_000):
                of, oid, d = (h[at : at + 100_000] for h in held)
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip([qid[of], oid, d, *np.zeros((3, len(of)), np.int64), k[of]], kinds)], names=names)
            of = np.flatnonzero(asked) if costs else np.zeros(0, np.int64)
            for at in range(0, len(of), 100_000):
                some = of[at : at + 100_000]
                yield pa.RecordBatch.from_arrays([pa.array(qid[some]), pa.nulls(len(some), pa.int64()), pa.nulls(len(some), pa.float64()), *(pa.array(c) for c in spent[some].T), pa.array(k[some], pa.int32())], names=names)

        part = packed.select("x1", "y0", "blob").mapInArrow(run, FOUND)
        out = part if out is None else out.union(part)
    return out


def merged(found: DataFrame, stats: bool) -> DataFrame:
    """qid, rank, oid, dist of the nearest k over all shards; with stats also evals, hops and tests, each query's sums over the shards."""
    best = W.partitionBy("qid").orderBy("dist", "oid")
    if stats:
        found = materialize(found, "found")
    top = found.where("oid is not null").withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= F.col("k")).select("qid", "rank", "oid", "dist")
    return top.join(found.groupBy("qid").agg(*[F.sum(c).alias(c) for c in ("evals", "hops", "tests")]), "qid") if stats else top


def search(index: DataFrame, queries: DataFrame, relation: Relation, ef: int = 64, swap: bool = False, mode: str = "walk", scan_below: int = 0, stats: bool = False, fan: int = 16) -> DataFrame:
    """qid, rank, oid, dist (and costs): the k nearest valid objects found for queries (qid, qvec, sq, tq, k), in an index as built or, without any shuffle of it, packed.

    A shard snaps the query to its own state, takes a valid entry or none, and walks; valid sets of up to scan_below objects are scanned.
    Shards' results are merged by (distance, oid): the union of the shards' valid sets is the whole valid set.
    mode `walk` follows labels; `post` ignores them and drops invalid results; `predicate` tests the relation at each node, passing through others;
    `dense` follows only valid neighbours, the nearest fan of each node's.
    Queries without vector or interval, or of another dimension, get no rows.
    """
    shards = index if "blob" in index.columns else pack(index)
    asked = attach_queries(queries, relation.plan(swap))
    many = lambda s, q, xq, yq, k: s.find_many(q, xq, yq, k, mode, scan_below, stats) if ef >= len(s.oid) and mode != "dense" else s.walk_many(q, xq, yq, k, ef, mode, scan_below, fan)
    return merged(each_shard(shards, asked, lambda s, q, xq, yq, k: s.find(q, xq, yq, k, ef, mode, scan_below, fan), many=many, costs=stats), stats)


def save(index: DataFrame, path: str, relation: Relation, **parameters) -> str:
    """Writes a new version of an index under path: its rows, sorted by shard and order, its packed shards, its entries and thresholds; and last one row of meta, which makes the version current. Returns the version."""
    spark, version = index.sparkSession, uuid.uuid4().hex
    at = f"{path}/{version}"
    index.repartition("shard").sortWithinPartitions("shard", "ord").write.partitionBy("shard").parquet(f"{at}/objects")
    rows = spark.read.schema(index.schema).parquet(f"{at}/objects")
    shards = rows.select("shard").distinct().count() or 1
    pack(rows).repartition(shards, "shard").write.parquet(f"{at}/shards")
    order = W.partitionBy("shard").orderBy("y", "oid").rowsBetween(W.unboundedPreceding, -1)  # a shard's rows
    tops = rows.withColumn("_m", F.max("x").over(order)).where(F.col("_m").isNull() | (F.col("x") > F.col("_m")))
    tops.select("shard", "ord", "oid", "x", "xr", "y", "yr").write.parquet(f"{at}/entries")
    axis = lambda c: rows.select("shard", F.lit(c).alias("axis"), F.col(c).alias("val"), F.col(f"{c}r").alias("rank")).distinct()
    axis("x").union(axis("y")).write.parquet(f"{at}/thresholds")
    terms = [f"{t.end}{t.op}{t.query}" for t in relation.terms]
    meta = spark.createDataFrame([(version, relation.name, terms, {k: str(v) for k, v in parameters.items()})], "version string, relation string, terms array<string>, parameters map<string,string>")
    meta.withColumn("written", F.current_timestamp()).write.mode("append").parquet(f"{path}/meta")
    return version


def load(spark: SparkSession, path: str, version: str | None = None) -> tuple[dict[str, DataFrame], Relation, dict]:
    """(tables objects, shards, entries and thresholds; relation; parameters) of a version, the last one written if none is named. A version without meta was never finished, and is not seen."""
    meta = spark.read.parquet(f"{path}/meta")
    row = (meta.where(F.col("version") == version) if version else meta.orderBy(F.col("written").desc(), "version").limit(1)).first()
    if row is None:
        raise ValueError(f"no version {version} of an index in {path}")
    tables = {t: spark.read.parquet(f"{path}/{row.version}/{t}") for t in ("objects", "shards", "entries", "thresholds")}
    return tables, custom(*row.terms, name=row.relation), dict(row.parameters)


def unlabelled(objects: DataFrame, relation: Relation, m: int = 16, pool: int = 200, shard_rows: int = 4000, gamma: int = 0) -> DataFrame:
    """A proximity graph whose edges carry no state, with the objects' coordinates, for the baselines that ignore labels: each object is swept once. gamma: no sweep, but edges to the m * gamma nearest objects, unpruned, for mode `dense`."""
    placed = assign(attach(whole(objects), relation.plan()), shard_rows).select("shard", "oid", "vec", "x", "y")

    def run(key, t):
        v, oid, x, y, xr, yr = _arrays(t)
        if gamma:
            near = kernels.dense(v, oid, m * gamma)
            rows = np.zeros((sum(len(u) for u in near), 6), np.int32)
            rows[:, 0], rows[:, 1] = np.repeat(np.arange(len(near)), [len(u) for u in near]), np.concatenate([*near, np.zeros(0, np.int64)])
        else:
            zero = np.zeros(len(oid), np.int64)
            rows = kernels.build(v, oid, zero, zero, m, "practical", pool, "full", "none")[0]
        return _rows(key[0].as_py(), v, oid, x, y, xr, yr, rows)

    return materialize(by_shard(placed).applyInArrow(run, KIND), "plain")
