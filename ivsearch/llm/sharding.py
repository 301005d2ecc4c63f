"""Sharding: minimax contiguous partition of atomic groups (equal texts) into near-equal shards."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import hidden, shown, stage, table

KEY_BITS = 63


def _ends(sums: np.ndarray, solid: np.ndarray, cap: float, shards: int, loose: bool) -> list[float]:
    """Greedy ends of the shards as positions in the row of segments; loose: segments of several groups may be cut anywhere."""
    upto, at, ends = np.concatenate([[0], np.cumsum(sums)]).astype(float), 0.0, []
    while at < len(sums) and len(ends) <= shards:
        i = int(at)
        done = upto[i] + (at - i) * sums[i]
        j = int(np.searchsorted(upto, done + cap, side="right")) - 1
        stop = float(j)
        if loose and j < len(sums) and not solid[j]:
            stop = j + (done + cap - upto[j]) / sums[j]
        if stop <= at:
            return [*ends, *[at] * (shards + 2)]
        at = min(stop, float(len(sums)))
        ends.append(at)
    return ends


def _least(sums, solid, shards: int, loose: bool) -> int:
    """The smallest capacity at which the greedy walk needs no more than shards, by bisection."""
    low, high = max(1, -(-int(sums.sum()) // shards)), int(sums.sum())
    low = max(low, int(sums[solid].max(initial=0)))
    while low < high:
        mid = (low + high) // 2
        low, high = (low, mid) if len(_ends(sums, solid, mid, shards, loose)) <= shards else (mid + 1, high)
    return low


def minimax_cuts(units: DataFrame, shards: int, first_bits: int = 12, step_bits: int = 6) -> tuple[list[int], int]:
    """Cuts (first keys of shards 1, 2, ...) of units (k: 63-bit key, bytes), in key order, with the least largest shard; and that size.

    The driver sees key ranges, never the units: 2^first_bits sums at first. A walk that may cut inside a range bounds the
    capacity from below, one that may not from above; only ranges where some shard can end between the two are split
    further, until both agree. What is gathered depends on the number of shards and on the bits, not on the data.
    """
    def sums(df: DataFrame, bits: int) -> np.ndarray:
        rows = df.groupBy(F.shiftright("k", KEY_BITS - bits).alias("p")).agg(F.sum("bytes").alias("s"), F.count(F.lit(1)).alias("n"), F.min("k").alias("lo")).collect()
        return np.array(sorted((r.lo, bits, r.p, r.s, r.n) for r in rows), dtype=np.int64).reshape(-1, 5)

    seg = sums(units, first_bits)
    while True:
        if not len(seg):
            return [], 0
        size, solid = seg[:, 3], (seg[:, 4] == 1) | (seg[:, 1] >= KEY_BITS)
        low, high = _least(size, solid, shards, True), _least(size, np.ones_like(solid), shards, False)
        if low == high:
            ends = _ends(size, np.ones_like(solid), high, shards, False)
            return [int(seg[int(e), 0]) for e in ends[:-1]], high
        early, late = (_ends(size, solid, c, shards, o) for c, o in ((low, False), (high, True)))
        open_ = np.zeros(len(seg), bool)
        for j in range(shards):
            a = early[j] if j < len(early) else len(seg)
            b = late[j] if j < len(late) else len(seg)
            open_[max(0, int(min(a, b)) - 1) : int(max(a, b)) + 1] = True
        open_ &= ~solid
        if not open_.any():
            open_ = ~solid
        parts = [seg[~open_]]
        for bits in np.unique(seg[open_, 1]):
            these = [int(x) for x in seg[open_ & (seg[:, 1] == bits), 2]]
            parts.append(sums(units.where(F.shiftright("k", KEY_BITS - int(bits)).isin(these)), min(KEY_BITS, int(bits) + step_bits)))
        seg = np.concatenate(parts)
        seg = seg[np.argsort(seg[:, 0], kind="stable")]


def shard(docs: DataFrame, shards: int = 24, bucket_rows: int = 20_000) -> DataFrame:
    """docs with size (UTF-8 bytes of the text plus 8), shard int and slot long; documents of equal text share a shard.

    Groups are ordered by a 63-bit hash of the text. A group of more than an even share of the bytes gets a shard of its own,
    first; the others are cut contiguously so that the largest of the remaining shards is as small as can be. Slots number
    the rows of a shard from 0: by fine hash buckets, whose row counts give each its first slot, so that no task sorts
    a shard, nor the copies of one text.
    Null texts are one group, of 8 bytes a row; empty texts another. Rows that repeat id and text stay together, in any
    order among themselves. An empty table gives no rows. Other columns pass through, whatever their names; columns named like the added ones are replaced.
    """
    added = ["size", "text_crc32", "shard", "slot"]
    rows_, names = hidden(docs, added)
    doc_id, text = names["doc_id"], names["text"]
    key = F.xxhash64(text).bitwiseAND(F.lit(2**KEY_BITS - 1))
    keyed = rows_.withColumns({"size": F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + 8, "k": key, "text_crc32": F.crc32(F.coalesce(text, F.lit("")).cast("binary"))})
    units = stage(keyed.groupBy("k").agg(F.sum("size").alias("bytes"), F.count(F.lit(1)).alias("n")), "units")
    total, rows = units.agg(F.coalesce(F.sum("bytes"), F.lit(0)), F.coalesce(F.sum("n"), F.lit(0))).first()
    big: dict[int, int] = {}
    while len(big) < shards - 1:  # at most one round for each shard
        left = total - sum(big.values())
        found = [r for r in units.where(F.col("bytes") * (shards - len(big)) > left).collect() if r.k not in big]  # fewer than shards
        if not found:
            break
        big |= {r.k: r.bytes for r in sorted(found, key=lambda r: (-r.bytes, r.k))[: shards - 1 - len(big)]}
    rest = units.where(~F.col("k").isin(list(big))) if big else units
    cuts, _ = minimax_cuts(rest, shards - len(big))
    number = F.lit(len(big)) + sum((F.when(F.col("k") >= c, 1).otherwise(0) for c in cuts), F.lit(0))
    for i, k in enumerate(big):
        number = F.when(F.col("k") == k, i).otherwise(number)
    buckets = max(16, rows // bucket_rows // shards)
    placed = keyed.withColumn("shard", number.cast("int")).withColumn("f", F.pmod(F.xxhash64(F.lit(5), "k", doc_id), F.lit(buckets)).cast("int"))
    counts = placed.groupBy(F.col("shard").alias("s"), F.col("f").alias("g")).agg(F.count(F.lit(1)).alias("n"))
    first = counts.withColumn("first", F.sum("n").over(W.partitionBy("s").orderBy("g")) - F.col("n")).drop("n")
    within = W.partitionBy("shard", "f").orderBy(doc_id, "text_crc32", "k")
    numbered = placed.withColumn("r", F.row_number().over(within) - 1).join(first, (F.col("shard") == F.col("s")) & (F.col("f") == F.col("g")))
    return numbered.select(*shown(names), "size", "text_crc32", "shard", (F.col("first") + F.col("r")).cast("long").alias("slot"))


def op5_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return shard(docs).select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
