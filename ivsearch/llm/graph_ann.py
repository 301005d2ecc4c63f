"""Approximate nearest neighbours: a robust-pruned directed graph in each shard, searched by beam."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import light_batches, stage, table


def _near(v: np.ndarray, sq: np.ndarray, q: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Squared distances, for each query, to its own row of ids."""
    return sq[ids] - 2 * np.einsum("bd,bkd->bk", q, v[ids]) + (q * q).sum(1)[:, None]


def beam(v: np.ndarray, sq: np.ndarray, graph: np.ndarray, q: np.ndarray, start: int, size: int) -> tuple[np.ndarray, np.ndarray]:
    """The size nearest nodes that a greedy walk from start meets, for many queries at once: ids and squared distances, nearest first.

    In each step every query that has unexpanded nodes in its beam expands the nearest. graph has -1 for no edge.
    """
    b, n = len(q), len(v)
    size = min(size, n)
    ids, far = np.full((b, size), -1, np.int64), np.full((b, size), np.inf)
    ids[:, 0], far[:, 0] = start, _near(v, sq, q, np.full((b, 1), start))[:, 0]
    done, met = np.zeros((b, size), bool), np.zeros((b, n + 1), bool)
    met[:, start] = met[:, n] = True
    while True:
        open_ = np.where(done | (ids < 0), np.inf, far)
        col = open_.argmin(1)
        act = np.flatnonzero(np.isfinite(open_[np.arange(b), col]))
        if not len(act):
            return ids, far
        done[act, col[act]] = True
        out = graph[ids[act, col[act]]]
        out = np.where(out < 0, n, out)
        new = ~met[act[:, None], out]
        met[act[:, None], out] = True
        dist = np.where(new, _near(v, sq, q[act], np.minimum(out, n - 1)), np.inf)
        all_far = np.concatenate([far[act], dist], 1)
        all_ids = np.concatenate([ids[act], np.where(new, out, -1)], 1)
        all_done = np.concatenate([done[act], np.zeros_like(new)], 1)
        best = np.argsort(all_far, 1, kind="stable")[:, :size]
        rows = np.arange(len(act))[:, None]
        far[act], ids[act], done[act] = all_far[rows, best], all_ids[rows, best], all_done[rows, best]
        ids[act] = np.where(np.isfinite(far[act]), ids[act], -1)


def robust_prune(v: np.ndarray, p: int, candidates: np.ndarray, degree: int, alpha: float) -> np.ndarray:
    """Up to degree diverse candidates of p: nearest first, each removing those it is nearer to, by the factor alpha, than p is."""
    c = np.unique(candidates)
    c = c[(c >= 0) & (c != p)]
    d = ((v[c] - v[p]) ** 2).sum(1)
    order = np.lexsort((c, d))
    c, d = c[order], d[order]
    between = np.maximum(0, (d0 := (v[c] ** 2).sum(1))[:, None] + d0 - 2 * v[c] @ v[c].T)
    alive, kept = np.ones(len(c), bool), []
    for i in range(len(c)):
        if alive[i]:
            kept.append(c[i])
            if len(kept) == degree:
                break
            alive &= alpha * alpha * between[i] > d
    return np.array(kept, np.int64)


def build(v: np.ndarray, degree: int, width: int, alpha: float, batch: int = 256) -> tuple[np.ndarray, int]:
    """Edges (n x degree, -1: none) and the entry, the node nearest to the mean: nodes are inserted in batches, in a seeded order.

    A batch's beams over the graph so far propose neighbours; pruning keeps diverse ones; each gets an edge back, and is pruned in turn when full.
    """
    n, sq = len(v), (v * v).sum(1)
    graph, used = np.full((n, degree), -1, np.int64), np.zeros(n, np.int64)
    start = int(((v - v.mean(0)) ** 2).sum(1).argmin())
    order = np.random.default_rng(7).permutation(n)
    order = np.concatenate([[start], order[order != start]])
    at = 1
    while at < n:
        todo = order[at : at + min(batch, max(1, at))]
        at += len(todo)
        ids, _ = beam(v, sq, graph, v[todo], start, width)
        back: dict[int, list[int]] = {}
        for p, c in zip(todo, ids):
            kept = robust_prune(v, p, np.concatenate([c, todo]) if at < 4 * batch else c, degree, alpha)
            graph[p, : len(kept)], used[p] = kept, len(kept)
            for x in kept:
                back.setdefault(int(x), []).append(int(p))
        for x, new in back.items():
            own = graph[x, : used[x]]
            new = [p for p in new if p not in own]
            if used[x] + len(new) > degree:
                kept = robust_prune(v, x, np.concatenate([own, new]), degree, alpha)
                graph[x] = -1
            else:
                kept = np.concatenate([own, new]).astype(np.int64)
            graph[x, : len(kept)], used[x] = kept, len(kept)
    return graph, start


SHARD = "shard int, ids binary, firsts binary, v binary, dim int, graph binary, start int"


def clean(df: DataFrame) -> DataFrame:
    """id long, v array<double>: rows with an id and a vector without null or non-finite components that is not zero."""
    fine = F.col("v").isNotNull() & F.forall("v", lambda y: y.isNotNull() & ~F.isnan(y) & (F.abs(y) < float("inf"))) & F.exists("v", lambda y: y != 0)
    return df.where(F.col("id").isNotNull() & fine).select(F.col("id").cast("long"), F.col("v").cast("array<double>"))


def index(vectors: DataFrame, k: int = 10, shard_rows: int = 4000, degree: int = 32, width: int = 64, alpha: float = 1.2) -> DataFrame:
    """One row for each shard of vectors (id, v), stored: its distinct vectors, the k + 1 smallest ids of each, its graph and entry (no graph: scan).

    Rows are dealt by a hash to shards of about shard_rows; each shard is one task. A vector found stands for all its ids, of which the k + 1 smallest
    can matter. Only vectors of the most frequent length (the shorter of equally frequent ones) count; of rows of one id, the smallest vector. Shards of max(4 k, 64) distinct vectors or fewer are scanned.
    """
    base = clean(vectors)
    length = base.groupBy(F.size("v").alias("n")).agg(F.count(F.lit(1)).alias("rows")).orderBy(F.col("rows").desc(), "n").first()
    base = base.where(F.size("v") == (length.n if length else 0)).groupBy("id").agg(F.min("v").alias("v"))
    shards = max(1, -(-base.count() // shard_rows))

    def make(key, t):
        ids = t.column("id").to_numpy()
        order = np.argsort(ids)
        ids = ids[order]
        flat = pa.concat_arrays([c.flatten() for c in t.column("v").chunks]).to_numpy(zero_copy_only=False).reshape(len(ids), -1)
        v, of = np.unique(flat[order] + 0.0, axis=0, return_inverse=True)  # + 0.0: no negative zeros
        by = np.argsort(of.ravel(), kind="stable")
        bounds = np.searchsorted(of.ravel()[by], np.arange(len(v) + 1))
        owners = [ids[by[a : min(b, a + k + 1)]] for a, b in zip(bounds[:-1], bounds[1:])]  # one of them may be the query's own
        graph, start = (np.zeros((0, 0), np.int32), 0) if len(v) <= max(4 * k, 64) else build(v, degree, width, alpha)
        firsts = np.concatenate([[0], np.cumsum([len(x) for x in owners])])
        row = {"shard": key[0].as_py(), "ids": np.concatenate(owners).astype("<i8").tobytes(), "firsts": firsts.astype("<i8").tobytes(), "v": v.tobytes(), "dim": v.shape[1], "graph": graph.astype("<i4").tobytes(), "start": start}
        return pa.Table.from_pylist([row], schema=pa.schema([("shard", pa.int32()), ("ids", pa.binary()), ("firsts", pa.binary()), ("v", pa.binary()), ("dim", pa.int32()), ("graph", pa.binary()), ("start", pa.int32())]))

    dealt = base.withColumn("shard", F.pmod(F.xxhash64("id"), F.lit(shards)).cast("int"))
    return stage(dealt.repartition(shards, "shard").groupBy("shard").applyInArrow(make, SHARD), "graphs")


def nearest(shards: DataFrame, queries: DataFrame, k: int = 10, beam_width: int = 160, block: int = 32_768, lanes: int = 1024) -> DataFrame:
    """query_id, rank (from 1), vec_id, score (Euclidean distance in double precision): the k nearest other rows found in stored shards for each query (id, v).

    Queries are a stated set. They are taken in blocks of about so many, each broadcast to the shards, which answer it by beam search; a block's results are
    written before the next is read, so nothing that is held at once grows with the queries. A shard's best k of each query are merged; distances are computed anew on the original vectors,
    ties go to smaller ids. Queries that clean() leaves out or whose length differs from the shards' get no rows.
    """
    spark = queries.sparkSession
    light_batches(spark)
    kind = "query_id long, vec_id long, score double"
    asked = stage(clean(queries).groupBy("id").agg(F.min("v").alias("v")).withColumn("h", F.xxhash64(F.lit(3), "id")), "asked")
    blocks = max(1, -(-asked.count() // block))

    def search_block(part: int) -> DataFrame:
        rows = asked.where(F.pmod("h", F.lit(blocks)) == part).select("id", "v").toArrow()  # about block rows
        sent = spark.sparkContext.broadcast((rows.column("id").to_numpy(), rows.column("v").to_pylist()))

        def run(batches):
            qid, qv = sent.value
            for b in batches:
                for r in b.to_pylist():
                    v = np.frombuffer(r["v"], np.float64).reshape(-1, r["dim"])
                    ids, firsts = np.frombuffer(r["ids"], "<i8"), np.frombuffer(r["firsts"], "<i8")
                    graph, sq = np.frombuffer(r["graph"], "<i4"), (v * v).sum(1)
                    graph = graph.reshape(len(v), -1) if len(graph) else graph
                    fit = np.array([i for i, x in enumerate(qv) if len(x) == r["dim"]], np.int64)
                    for at in range(0, len(fit), lanes):
                        some = fit[at : at + lanes]
                        q = np.array([qv[i] for i in some], np.float64)
                        met = beam(v, sq, graph, q, r["start"], beam_width)[0] if len(graph) else np.tile(np.arange(len(v)), (len(some), 1))
                        out = ([], [], [])
                        for one, own, c in zip(q, qid[some].tolist(), met):
                            c = c[c >= 0]
                            d = np.sqrt(((v[c] - one) ** 2).sum(1))
                            n = firsts[c + 1] - firsts[c]
                            found = np.concatenate([ids[firsts[x] : firsts[x + 1]] for x in c])
                            d, found = np.repeat(d, n)[found != own], found[found != own]
                            best = np.lexsort((found, d))[:k]
                            for o, x in zip(out, (np.full(len(best), own), found[best], d[best])):
                                o.append(x)
                        cols = [np.concatenate(o) for o in out]
                        yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.float64())], ["query_id", "vec_id", "score"])

        best = W.partitionBy("query_id").orderBy("score", "vec_id")
        found = shards.repartition(shards.count() or 1, "shard").mapInArrow(run, kind)
        return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")

    if blocks == 1:
        return search_block(0)
    parts = [stage(search_block(i), "nearest") for i in range(blocks)]
    return spark.read.schema(parts[0].schema).parquet(*{f.rsplit("/", 1)[0] for p in parts for f in p.inputFiles()})


def search(vectors: DataFrame, queries: DataFrame, k: int = 10, shard_rows: int = 4000, degree: int = 32, width: int = 64, alpha: float = 1.2, beam_width: int = 160) -> DataFrame:
    """nearest() over index(). Null and zero vectors, vectors of another length than most and those with null or non-finite components take no part. Equal vectors under different ids all count; rows of one id count once, by the smallest vector. Extra columns are ignored."""
    return nearest(index(vectors, k, shard_rows, degree, width, alpha), queries, k, beam_width)


def op9_graph_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v"))
    return search(rows, rows.where("id % 100 = 0"))
