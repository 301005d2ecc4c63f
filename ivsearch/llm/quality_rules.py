"""Quality rules with risk-controlled thresholds, set on labelled holdouts by exact binomial bounds."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import BLANKS, WORD, hidden, shown, small, stage, table

SYMBOLS = "#*$%&|<>"
#: Rule names; each has an integer score from 0 to 1000 that grows with suspicion.
RULES = ("symbols", "dup_lines", "repeats", "capitals", "long_words", "short_words")


def _without(text: str, chars: str) -> Column:
    return F.length(F.translate(text, chars, ""))


def measures(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with the base measures of their whole texts, null as empty: n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, and n_lines (with a word), n_capitals.

    n_repeat_words counts the words that lie in some three-word window occurring at least twice in the text. Windows are
    hashed to 64 bits and sorted with their places inside the row; equal neighbours are repeats, and the words covered
    are summed from the gaps between their sorted places. All of it stays in one row: no shuffle, no Python.
    Columns of docs with these names are replaced; others pass through, whatever their names.
    """
    added = ["n_words", "n_repeat_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_capitals"]
    a, names = hidden(docs, added)
    a = a.withColumn("t", F.coalesce(F.col(names[text]), F.lit(""))).withColumn("w", F.regexp_extract_all("t", F.lit(WORD), F.lit(0)))
    a = a.withColumn("n_words", F.size("w").cast("long"))
    at = lambda i: F.get("w", i)
    a = a.withColumn("h", F.when(F.col("n_words") < 3, F.array().cast("array<bigint>")).otherwise(F.transform(F.sequence(F.lit(0), F.greatest(F.size("w") - 3, F.lit(0))), lambda i: F.xxhash64(at(i), at(i + 1), at(i + 2)))))
    a = a.withColumn("some", F.size(F.array_distinct("h")) < F.size("h"))
    a = a.withColumn("s", F.when(F.col("some"), F.array_sort(F.transform("h", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))))
    same = lambda x, i: F.coalesce(F.get("s", i)["h"] == x["h"], F.lit(False))
    a = a.withColumn("p", F.when(F.col("some"), F.array_sort(F.transform(F.filter("s", lambda x, i: same(x, i - 1) | same(x, i + 1)), lambda x: x["i"]))))
    covered = F.aggregate(F.transform("p", lambda p, i: F.least(F.coalesce(F.get("p", i + 1) - p, F.lit(3)), F.lit(3))), F.lit(0), lambda x, y: x + y)
    a = a.withColumn("l", F.filter(F.split("t", "\n"), lambda x: F.btrim(x, F.lit(BLANKS)) != ""))
    return a.select(
        *shown(names), "n_words",
        F.coalesce(covered, F.lit(0)).cast("long").alias("n_repeat_words"),
        _without("t", BLANKS).cast("long").alias("word_chars"),
        (F.length("t") - _without("t", SYMBOLS)).cast("long").alias("n_symbols"),
        F.size("l").cast("long").alias("n_lines"),
        (F.size("l") - F.size(F.array_distinct("l"))).cast("long").alias("n_dup_lines"),
        (F.length("t") - _without("t", "ABCDEFGHIJKLMNOPQRSTUVWXYZ")).cast("long").alias("n_capitals"),
    )


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def scores() -> dict[str, Column]:
    """Integer arithmetic only, so that any engine gives the same."""
    part = lambda x, y: F.coalesce(F.expr(f"least(1000 * {x} div nullif({y}, 0), 1000L)"), F.lit(0))
    mean = F.coalesce(F.expr("least(10 * word_chars div nullif(n_words, 0), 1000L)"), F.lit(0))
    return {
        "symbols": part("n_symbols", "word_chars"), "dup_lines": part("n_dup_lines", "n_lines"), "repeats": part("n_repeat_words", "n_words"),
        "capitals": part("n_capitals", "word_chars"), "long_words": mean, "short_words": 1000 - mean,
    }


def allowed(n: Column, alpha: float, level: Column) -> Column:
    """The largest k for which k or fewer false rejections of n good documents refute a rate of alpha at the level: P(Bin(n, alpha) <= k) <= level; null if none.

    The terms are carried as logarithms from one to the next, so no n underflows the first.
    """
    first = n * F.lit(math.log1p(-alpha))
    odds = math.log(alpha) - math.log1p(-alpha)
    start = F.struct(first.alias("log"), F.lit(0.0).alias("sum"), F.lit(-1).cast("long").alias("k"))

    def step(s: Column, i: Column) -> Column:
        total = s["sum"] + F.exp(s["log"])
        return F.struct(
            (s["log"] + F.log((n - i).cast("double") / (i + 1)) + F.lit(odds)).alias("log"), total.alias("sum"),
            F.when(total <= level, i).otherwise(s["k"]).alias("k"),
        )

    last = F.aggregate(F.sequence(F.lit(0).cast("long"), F.floor(n * alpha)), start, step)["k"]
    return F.when(last >= 0, last)


def thresholds(good: DataFrame, alpha: float = 0.005, delta: float = 0.05) -> DataFrame:
    """Cutoffs (stratum, rule, cutoff) from good documents (stratum and a column for each rule): a score above the cutoff rejects.

    For each stratum and rule, cutoffs are tried from the most lenient to the strictest score seen, and the last is taken
    for which the number of good documents above it still refutes, by the exact binomial test, that more than alpha of good
    ones would be rejected. False rejections grow along that fixed sequence, so testing it needs no correction; rules
    and strata are corrected by Bonferroni, delta / (rules * strata) each. A stratum with too few good documents has no
    cutoff and rejects nothing. Counts are aggregated to at most 1,001 scores a rule before any window.
    """
    flat = good.select("stratum", F.explode(F.array(*[F.struct(F.lit(r).alias("rule"), F.col(r).cast("long").alias("score")) for r in RULES])).alias("x")).select("stratum", "x.*")
    counts = flat.groupBy("stratum", "rule", "score").agg(F.count(F.lit(1)).alias("n"))
    by = W.partitionBy("stratum", "rule")
    strata = counts.select("stratum").distinct().agg(F.greatest(F.count(F.lit(1)), F.lit(1)).alias("strata"))
    ranked = counts.withColumns({"good": F.sum("n").over(by), "above": F.sum("n").over(by.orderBy(F.col("score").desc())) - F.col("n")})
    sizes = ranked.groupBy("stratum").agg(F.max("good").alias("of")).crossJoin(F.broadcast(strata))  # one row with the number of strata
    ks = sizes.withColumn("level", F.lit(delta) / len(RULES) / F.col("strata")).withColumn("k", allowed(F.col("of"), alpha, F.col("level")))
    return ranked.join(ks.select("stratum", "k"), "stratum").where(F.col("above") <= F.col("k")).groupBy("stratum", "rule").agg(F.min("score").alias("cutoff"))


def pooled(good: DataFrame, strata: DataFrame, alpha: float, delta: float) -> DataFrame:
    """(stratum, pool) for each of strata: its own name, or that of the common pool if it has too few rows in good for any cutoff of its own.

    What has enough is decided by the counts alone, at the level that holds with all strata apart; pooling only makes strata fewer.
    """
    n = strata.join(good.groupBy("stratum").agg(F.count(F.lit(1)).alias("n")), "stratum", "left").withColumn("n", F.coalesce("n", F.lit(0)))
    level = F.lit(delta) / len(RULES) / F.col("strata")
    n = n.crossJoin(F.broadcast(strata.agg(F.count(F.lit(1)).alias("strata"))))  # one row with the number of strata
    return n.select("stratum", F.when(F.col("n") * F.lit(math.log1p(-alpha)) <= F.log(level), F.col("stratum")).otherwise(F.lit("\0few")).alias("pool"))


def judge(docs: DataFrame, labels: DataFrame, alpha: float = 0.005, delta: float = 0.05) -> DataFrame:
    """docs with the measures, base_failed and kept. Strata are languages (null: one of its own); quality 1 in labels (doc_id, quality) marks good documents.

    A document is kept if it passes the base rules and none of its scores is above its stratum's cutoff. alpha bounds the false rejections of each rule,
    so with six rules a stratum falsely rejects at most 6 * alpha (3%) of its good documents that pass the base rules, all with confidence 1 - delta. Languages with too few good
    documents for a cutoff of their own are pooled into one stratum; there, alpha holds for the pool, not for each language.
    Null text is empty and fails the base rules. Documents with null id have no label. Repeated labels of an id count
    once, as good if any is; repeated documents are judged alike. No labels: the base rules alone decide.
    """
    stratum = F.coalesce(F.col("lang"), F.lit("\0none")) if "lang" in docs.columns else F.lit("\0all")
    kept = docs.drop("base_failed", "kept")
    seen = stage(measures(kept.select("doc_id", "text", stratum.alias("stratum"))).withColumns(scores()).drop("text"), "rules")
    ids = labels.where("quality = 1").select(F.col("doc_id").alias("_id")).distinct()
    good = seen.where(~base_failed()).join(ids, F.col("doc_id") == F.col("_id"), "left_semi")
    pools = stage(pooled(good, seen.select("stratum").distinct(), alpha, delta), "pools")
    good = good.join(small(pools), "stratum").drop("stratum").withColumnRenamed("pool", "stratum")
    cut = stage(thresholds(good, alpha, delta).groupBy("stratum").pivot("rule", list(RULES)).agg(F.min("cutoff")).withColumnsRenamed({r: f"{r}_cut" for r in RULES}), "cutoffs")
    cut = pools.join(small(cut.withColumnRenamed("stratum", "pool")), "pool", "left").drop("pool")
    passed = ~base_failed()
    for r in RULES:
        passed = passed & (F.col(f"{r}_cut").isNull() | (F.col(r) <= F.col(f"{r}_cut")))
    return seen.join(small(cut), "stratum", "left").withColumns({"base_failed": base_failed(), "kept": passed})


def filter_documents(docs: DataFrame, labels: DataFrame, **how) -> DataFrame:
    """The rows of docs that judge() keeps; rows of one id stay or go together, by the worst."""
    bad = judge(docs, labels, **how).where(~F.col("kept")).select(F.col("doc_id").alias("id")).distinct()
    rows, names = hidden(docs)
    return rows.join(bad, F.col(names["doc_id"]).eqNullSafe(F.col("id")), "left_anti").select(*shown(names))


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    return judge(docs, table(spark, sf_dir, "labels").select("doc_id", "quality")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")
