"""Experiments as driver queries: exact counts, and whether what is measured goes the way it is reported to go. Their SQL gives the counts and says that it does."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import experiments as x

LOW, SIGMAS = 0.01, (0.01, 0.1)


def judged(df, ok, *columns):
    """columns and as_reported; ok compares each row with the others of its selectivity, where w(method) is a method's recall."""
    own = W.partitionBy("sigma")
    w = lambda method: F.max(F.when(F.col("method") == method, F.col("recall"))).over(own)
    return df.withColumn("as_reported", F.coalesce(ok(w), F.lit(False))).select(*columns, "as_reported")


def methods(name):
    def run(spark, sf_dir):
        """The labelled walk stays accurate where valid sets are small, walks that ignore labels do not, exact methods are exact, and nothing invalid is returned."""
        def ok(w):
            walk, r = w("walk"), F.col("recall")
            # At a hundredth the methods without labels lose most; at a tenth the denser graph catches up.
            free = F.when(F.col("method") == "dense", (F.col("sigma") > LOW) | (r <= walk)).otherwise(r < walk)
            return (F.col("invalid") == 0) & F.when(F.col("method").isin("scan", "tree"), r >= 0.99).when(F.col("method") == "walk", r >= 0.9).otherwise(free)

        return judged(x.methods(spark, sf_dir, "syn", name, SIGMAS, ef=32), ok, "sigma", "method", "queries", "valid")

    return run


def along(parameter, ok, get):
    """parameter's value and whether its row, in the order of the rows, is as reported; ok gets the list of rows."""
    def run(spark, sf_dir):
        rows = get(spark, sf_dir).collect()
        return spark.createDataFrame([(str(r["params"][parameter] if "params" in r else r[parameter]), bool(good)) for r, good in zip(rows, ok(rows))], "value string, as_reported boolean")

    return run


def _patch(rows):
    by = {r["params"]["patch"]: r["recall"] for r in rows}
    return [by["none"] < by["anchored"] and by["anchored"] >= 0.9] + [by[p] <= by["anchored"] + 0.02 for p in ("previous", "lifetime", "anchored")]


def _falls(key):
    return lambda rows: [i == 0 or r[key] <= rows[i - 1][key] for i, r in enumerate(rows)]


def _rises(key, slack=0.02):
    return lambda rows: [i == 0 or r[key] >= rows[i - 1][key] - slack for i, r in enumerate(rows)]


def _linear(rows):
    """Edges an object grow by less than a half where objects double."""
    return [i == 0 or r["edges"] / r["objects"] <= 1.5 * rows[i - 1]["edges"] / rows[i - 1]["objects"] for i, r in enumerate(rows)]


def _sizes(rows):
    """The labelled index is larger than a plain graph; the dense graph has the most edges of the two plain ones."""
    by = {(r["dataset"], r["method"]): r for r in rows}
    return [by[r["dataset"], "post"]["bytes"] < by[r["dataset"], "walk"]["bytes"] and by[r["dataset"], "post"]["edges"] < by[r["dataset"], "dense"]["edges"] and r["bytes"] > 0 for r in rows]


PATCHES, LEAPS, KPS, WIDTHS, KINDS, PREFIXES = ("none", "previous", "lifetime", "anchored"), ("full", "conservative", "aggressive", "max"), (1, 8, 32), (10, 64, 512), ("uniform", "normal", "skewed", "clustered", "hollow"), (125, 500)
BUILT = ("post", "dense", "tree", "walk")

QUERIES = {
    "exp_methods_contained": methods("contained"),
    "exp_methods_overlaps": methods("overlaps"),
    "exp_patch_ablation": along("patch", _patch, lambda s, d: x.variants(s, d, "patch", PATCHES, sigma=LOW, ef=32, pool=20)),
    "exp_leap_ablation": along("leap", _falls("edges"), lambda s, d: x.variants(s, d, "leap", LEAPS, sigma=0.1, ef=32)),
    "exp_repair_pool": along("kp", _rises("recall"), lambda s, d: x.variants(s, d, "kp", KPS, sigma=LOW, ef=32, pool=20)),
    "exp_constructors": along("construct", lambda rows: [r["recall"] >= 0.9 and r["invalid"] == 0 for r in rows], lambda s, d: x.variants(s, d, "construct", ("exact", "incremental"), sigma=0.1, ef=64)),
    "exp_broad_search_pool": along("pool_by", lambda rows: [r["recall"] >= 0.9 and r["invalid"] == 0 for r in rows], lambda s, d: x.variants(s, d, "pool_by", ("scan", "graph"), sigma=0.1, ef=64)),
    "exp_search_width": along("ef", _rises("recall", 0.01), lambda s, d: x.widths(s, d, WIDTHS)),
    "exp_distributions": along("distribution", lambda rows: [r["recall"] >= 0.9 for r in rows], lambda s, d: x.distributions(s, d, sigmas=(0.1,), ef=64)),
    "exp_prefixes": along("prefix", _linear, lambda s, d: x.prefixes(s, d, PREFIXES)),
    "exp_build_table": along("method", _sizes, lambda s, d: x.build_table(s, d, ("syn",), which=BUILT)),
}


def sql(workload) -> dict[str, str]:
    """workload(name, sigma, view) is the SQL of made."""
    def counts(name):
        ms = x.METHODS if name == "contained" else tuple(m for m in x.METHODS if m != "tree")
        one = lambda s: f"SELECT {s}::DOUBLE AS sigma, v.method, n AS queries, valid, TRUE AS as_reported FROM (VALUES {', '.join(repr((m,)).replace(',)', ')') for m in ms)}) v(method), (SELECT count(*) AS n, sum(realised)::BIGINT AS valid FROM ({workload(name, s, 'syn')} SELECT * FROM made) WHERE sq IS NOT NULL)"
        return " UNION ALL ".join(one(s) for s in SIGMAS)

    said = lambda values: "SELECT value, TRUE AS as_reported FROM (VALUES " + ", ".join(f"('{v}')" for v in values) + ") v(value)"
    return {
        "exp_methods_contained": counts("contained"), "exp_methods_overlaps": counts("overlaps"), "exp_patch_ablation": said(PATCHES), "exp_leap_ablation": said(LEAPS), "exp_repair_pool": said(KPS),
        "exp_constructors": said(("exact", "incremental")), "exp_broad_search_pool": said(("scan", "graph")), "exp_search_width": said(WIDTHS), "exp_distributions": said(KINDS), "exp_prefixes": said(PREFIXES), "exp_build_table": said(BUILT),
    }
