"""Mixing sources to target weights: capped water-filling, then whole and fractional repetitions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import WORD, hidden, n_words, shown, small, stage, table


def water_fill(sources: DataFrame, weights=(3, 1, 2), share: float = 1.5, max_epochs: int = 2) -> DataFrame:
    """Targets of sources (source, source_size), one row each.

    Weights go round in code point order of the sources, null last. All targets sum to share * all sizes,
    none exceeds max_epochs * its source's size. Sources sorted by cap over weight are saturated in that order,
    so the fixed point of "clamp, then reshare the excess by weight" is found by two running sums over one row
    per source: no iteration. The windows hold one row per source.
    Adds weight int, target double. Empty input gives no rows; sources without words get 0.
    """
    order, rest = W.orderBy(F.col("source").asc_nulls_last()), W.orderBy(F.col("cap") / F.col("weight"), "rank")
    every, before = W.partitionBy(), rest.rowsBetween(W.unboundedPreceding, -1)
    cycle = F.array(*[F.lit(int(w)) for w in weights])
    full = F.col("cap") * F.col("left_weight") <= F.col("weight") * F.col("left_words")
    return (
        sources.withColumn("rank", F.row_number().over(order))
        .withColumn("weight", F.element_at(cycle, ((F.col("rank") - 1) % len(weights) + 1).cast("int")))
        .withColumn("cap", F.col("source_size") * F.lit(int(max_epochs)))
        .withColumn("left_words", F.sum("source_size").over(every) * F.lit(float(share)) - F.coalesce(F.sum("cap").over(before), F.lit(0)))
        .withColumn("left_weight", F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0)))
        .withColumn("full", full)
        .withColumn("free", F.max(F.when(~F.col("full"), F.struct(F.col("left_words") / F.col("left_weight"), "left_words", "left_weight"))).over(every))
        .withColumn("target", F.when(F.col("full"), F.col("cap").cast("double")).otherwise(F.col("weight") * F.col("free.left_words") / F.col("free.left_weight")))
        .select("source", "source_size", "weight", "target")
    )


def plan(docs: DataFrame, weights=(3, 1, 2), share: float = 1.5, max_epochs: int = 2, seed: str = "mix", buckets: int = 4096) -> DataFrame:
    """docs with size, source_size, target, whole (repetitions of all its words) and part (words of one more, cut repetition).

    A source's target is whole repetitions of all its documents and q words more. Those come from its documents in
    seeded hash order up to q words; the document where q falls is cut. q is located in a histogram of
    (source, hash bucket) and then inside the one bucket it falls in, so a source with any share of the rows is
    never sorted in one task; documents are not shuffled.
    Null source is a source of its own, null text has size 0. Rows that repeat id and text share their place in
    the order; if q falls on them, they get their words in turn, in the order in which they are read, so that q is met to the word. Rows
    without id are ordered by their texts. Needs doc_id, text, source; other columns pass through, whatever their names,
    unless they are one of the added names, which are replaced.
    """
    rows, names = hidden(docs, ["size", "source_size", "target", "whole", "part"])
    doc_id, text = names["doc_id"], names["text"]
    crc = F.crc32(F.coalesce(text, F.lit("")).cast("binary"))
    key = F.struct(F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col(doc_id).cast("string"), F.concat(F.lit("-"), crc.cast("string"))))).alias("h"), F.col(doc_id).alias("d"), crc.alias("t"))
    bucket = F.conv(F.substring("key.h", 1, 6), 16, 10).cast("long") % buckets
    sized = stage(rows.select(F.col(names["source"]).alias("source"), n_words(text).alias("size"), key.alias("key")).withColumn("bucket", bucket), "mix")
    histogram = stage(sized.groupBy("source", "bucket").agg(F.sum("size").alias("words")), "mixhist")
    targets = water_fill(histogram.groupBy("source").agg(F.sum("words").alias("source_size")), weights, share, max_epochs)
    need = F.floor(F.col("target") + 0.5)
    targets = stage(
        targets.withColumn("whole", F.when(F.col("source_size") > 0, F.floor(need / F.col("source_size"))).otherwise(F.lit(0)))
        .withColumn("q", need - F.col("whole") * F.col("source_size")),
        "mixtarget",
    )
    running = W.partitionBy("source").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)
    t, h = targets.alias("t"), histogram.withColumn("before", F.coalesce(F.sum("words").over(running), F.lit(0))).alias("h")
    hit = t.join(h, F.col("t.source").eqNullSafe(F.col("h.source")) & (F.col("before") < F.col("q")) & (F.col("before") + F.col("words") >= F.col("q"))).select("t.source", "h.bucket", (F.col("q") - F.col("before")).alias("q"))
    inner = W.partitionBy("source", "bucket").orderBy("key").rowsBetween(W.unboundedPreceding, W.currentRow)
    last = (
        sized.alias("s").join(small(hit).alias("h"), F.col("s.source").eqNullSafe(F.col("h.source")) & (F.col("s.bucket") == F.col("h.bucket")))
        .groupBy("h.source", "h.bucket", "q", "key").agg(F.sum("size").alias("size"), F.count(F.lit(1)).alias("rows"))
        .withColumn("upto", F.sum("size").over(inner))
        .where((F.col("upto") >= F.col("q")) & (F.col("upto") - F.col("size") < F.col("q")))
        .select("source", "bucket", F.struct("key", (F.col("q") - F.col("upto") + F.col("size")).alias("part"), "rows").alias("cut"))
    )
    cuts = stage(t.join(last.alias("l"), F.col("t.source").eqNullSafe(F.col("l.source")), "left").select("t.*", F.col("l.bucket").alias("cut_bucket"), "l.cut"), "mixcut")
    placed = rows.withColumns({"size": n_words(text), "key": key}).withColumn("bucket", bucket)
    at_cut = (F.col("q") > 0) & (F.col("bucket") == F.col("cut_bucket")) & (F.col("key") == F.col("cut.key"))
    part = (
        F.when((F.col("q") <= 0) | F.col("cut").isNull(), F.lit(0))
        .when((F.col("bucket") < F.col("cut_bucket")) | ((F.col("bucket") == F.col("cut_bucket")) & (F.col("key") < F.col("cut.key"))), F.col("size"))
        .when(F.col("key") == F.col("cut.key"), F.least("size", "cut.part")).otherwise(F.lit(0))
    )
    met = placed.join(small(cuts), F.col(names["source"]).eqNullSafe(F.col("source")), "left")
    out = [*names.values(), "size", "source_size", "target", F.col("whole").cast("long").alias("whole")]
    final = lambda df: df.select(*shown(names), "size", "source_size", "target", "whole", "part")
    one = met.select(*out, part.cast("long").alias("part"))
    if cuts.where("cut.rows > 1").isEmpty():
        return final(one)
    shared = F.coalesce(at_cut & (F.col("cut.rows") > 1), F.lit(False))
    tied = stage(met.where(shared).select(*out, F.col("source"), F.col("cut.part").alias("left"), F.monotonically_increasing_id().alias("at")), "mixtied")
    return final(met.where(~shared).select(*out, part.cast("long").alias("part")).union(in_turn(tied).select(*one.columns)))


def in_turn(tied: DataFrame) -> DataFrame:
    """tied (source, size, left: words that a source's rows share, at: place, with the task in the upper bits) with part: rows get all their words in turn until left is used up. No window holds more than one task's rows or one row for each task."""
    tied = tied.withColumn("task", F.shiftright("at", 33))
    task = tied.groupBy("source", "task").agg(F.sum("size").alias("words"))
    earlier = task.withColumn("earlier", F.coalesce(F.sum("words").over(W.partitionBy("source").orderBy("task").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).select(F.col("source").alias("of_source"), F.col("task").alias("of_task"), "earlier")
    own = F.coalesce(F.sum("size").over(W.partitionBy("source", "task").orderBy("at").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    given = tied.withColumn("own", own).join(small(earlier), F.col("source").eqNullSafe(F.col("of_source")) & (F.col("task") == F.col("of_task")))
    return given.withColumn("part", F.greatest(F.lit(0), F.least("size", F.col("left") - F.col("earlier") - F.col("own"))).cast("long"))


def mix(docs: DataFrame, **how) -> DataFrame:
    """The mixed corpus, with the columns of docs: a row per whole repetition, and the first words of a cut one."""
    rows, names = hidden(docs)
    own = {c: names[c] for c in ("doc_id", "text", "source")}
    p = plan(rows.withColumnsRenamed({u: c for c, u in own.items()}), **how)
    cut = F.array_join(F.slice(F.regexp_extract_all("text", F.lit(WORD), F.lit(0)), 1, F.col("part").cast("int")), " ")
    extra = F.when(F.col("part") <= 0, F.array().cast("array<string>")).when(F.col("part") == F.col("size"), F.array("text")).otherwise(F.array(cut))
    copies = p.withColumn("copy", F.explode(F.concat(F.array_repeat(F.col("text"), F.col("whole").cast("int")), extra)))
    return copies.select(*shown(names | {c: c for c in own}, text=F.col("copy")))


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    return plan(docs).select("doc_id", "size", "source_size", "target", (F.col("whole") * F.col("size") + F.col("part")).alias("taken"))


SQL = r"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size, md5('mix:' || doc_id::VARCHAR) AS h FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
r AS (SELECT *, row_number() OVER (ORDER BY source ASC NULLS LAST) AS rank FROM s),
w AS (SELECT *, CASE (rank - 1) % 3 WHEN 0 THEN 3 WHEN 1 THEN 1 ELSE 2 END AS weight, source_size * 2 AS cap FROM r),
l AS (SELECT *, (sum(source_size) OVER ())::DOUBLE * 1.5 - coalesce(sum(cap) OVER o, 0)::DOUBLE AS left_words,
        (sum(weight) OVER () - coalesce(sum(weight) OVER o, 0))::DOUBLE AS left_weight
      FROM w WINDOW o AS (ORDER BY cap::DOUBLE / weight, rank ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
f AS (SELECT *, cap * left_weight <= weight * left_words AS is_full FROM l),
t AS (SELECT source, source_size, CASE WHEN is_full THEN cap::DOUBLE ELSE weight
        * (SELECT arg_max(left_words, left_words / left_weight) FROM f WHERE NOT is_full)
        / (SELECT arg_max(left_weight, left_words / left_weight) FROM f WHERE NOT is_full) END AS target FROM f),
n AS (SELECT *, CASE WHEN source_size > 0 THEN floor(floor(target + 0.5) / source_size)::BIGINT ELSE 0 END AS whole FROM t),
q AS (SELECT *, floor(target + 0.5)::BIGINT - whole * source_size AS q FROM n),
c AS (SELECT d.doc_id, d.size, q.source_size, q.target, q.whole, q.q,
        coalesce(sum(d.size) OVER (PARTITION BY d.source ORDER BY ('0x' || substr(h, 1, 6))::BIGINT % 4096, h, d.doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS before
      FROM d JOIN q ON d.source IS NOT DISTINCT FROM q.source)
SELECT doc_id, size, source_size, target, (whole * size + greatest(0, least(size, q - before)))::BIGINT AS taken FROM c
"""
