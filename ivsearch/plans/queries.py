"""Queries over the given tables, one or more for each method, and SQL that gives the same rows."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import coords, relations, vectors
from ..operators import audit, exact, index, interval_tree, measure
from ..session import materialize, number
from ..streaming import sessions as streams
from .workload import MICROS, exact_count, features, objects, synth

REL, VIEWS, WIDE = relations.ALL, ("price", "ship", "syn"), ("orders", "partyear", "docs")
SIGMAS = {"0001": 0.001, "001": 0.01, "005": 0.05, "010": 0.1, "050": 0.5}
#: Every selectivity for the two main relations, one for the others.
WORKLOADS = [(r, tag, sigma) for r in REL for tag, sigma in SIGMAS.items() if r in ("contained", "overlaps") or tag == "001"]
#: Relations beyond the five named ones: the same end of the data twice, and ends against the other end of the query.
CUSTOM = {"start_inside": ("s>=sq", "s<=tq"), "end_inside": ("t>=sq", "t<=tq"), "started": ("s<=sq", "s<=tq"), "mixed": ("t<=tq", "s>=tq")}
ALL_OF_THEM = 1 << 20  # a pool as large as any valid set: what a connected graph then returns is exact


def rounded(df: DataFrame) -> DataFrame:
    return df.select("qid", F.col("rank").cast("long").alias("rank"), "oid", F.round("dist", 6).alias("dist"))


def valid_counts(name, view):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        o, q = objects(spark, sf_dir, view, name)
        return measure.selectivity(o, q, REL[name]).select("qid", "valid")

    return run


def truth(name, view="price", how=exact.filtered_knn):
    def run(spark, sf_dir):
        o, q = objects(spark, sf_dir, view, name)
        return rounded(how(o, q, REL[name] if name else None))

    return run


def graph_search(name, ef, method="practical", mode="walk", view="price", **how):
    def run(spark, sf_dir):
        o, q = (materialize(t, "view") for t in objects(spark, sf_dir, view, name))  # each is read several times, and is an aggregate of all lines
        if mode == "walk":
            g = materialize(index.build(o, REL[name], 8, method, 100, **how), "index")
        else:
            g = index.unlabelled(o, REL[name], 12, 100)
        return rounded(index.search(g, q, REL[name], ef, mode=mode))

    return run


def tree(spark, sf_dir):
    o, q = objects(spark, sf_dir)
    return rounded(interval_tree.search(interval_tree.build(o), q, ef=ALL_OF_THEM))


def payload(spark, sf_dir):
    o, q = objects(spark, sf_dir)
    labels = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").alias("oid"), "label")
    return rounded(exact.filtered_knn(o.join(labels, "oid"), q, REL["overlaps"], F.col("label") == 3))


def custom_counts(terms):
    def run(spark, sf_dir):
        o, q = objects(spark, sf_dir, "syn")
        return measure.selectivity(o, q.withColumns({"sq": F.col("sq") - 100_000, "tq": F.col("tq") + 100_000}), relations.custom(*terms)).select("qid", "valid")

    return run


def scalar_range(spark, sf_dir):
    """The scalar range-labelled graph: one attribute, s, twice."""
    o, q = objects(spark, sf_dir, "syn")
    r = relations.custom(*CUSTOM["start_inside"])
    q = q.withColumns({"sq": F.col("sq") - 100_000, "tq": F.col("tq") + 100_000})
    return rounded(index.search(materialize(index.pack(index.build(o, r, 8, "practical", 100)), "packed"), q, r, ALL_OF_THEM))


def swapped(spark, sf_dir):
    o, q = objects(spark, sf_dir)
    return rounded(index.search(index.build(o, REL["contained"], 8, "practical", 100, swap=True), q, REL["contained"], ALL_OF_THEM, swap=True))


def dated(spark, sf_dir):
    """Endpoints and queries as timestamps."""
    o, q = objects(spark, sf_dir, "ship")
    at = lambda *cs: {c: F.timestamp_micros(F.col(c).cast("long")) for c in cs}
    return rounded(index.search(index.build(o.withColumns(at("s", "t")), REL["overlaps"], 8, "practical", 100), q.withColumns(at("sq", "tq")), REL["overlaps"], ALL_OF_THEM))


def states(spark, sf_dir):
    o, q = objects(spark, sf_dir)
    plan = REL["contained"].plan()
    return coords.snap(coords.attach_queries(q, plan), coords.attach(o, plan)).select("qid", "a", "c")


def threshold_lists(spark, sf_dir):
    o, _ = objects(spark, sf_dir, "ship")
    o = coords.attach(o, REL["after"].plan())
    return coords.thresholds(o, "x").withColumn("axis", F.lit("x")).union(coords.thresholds(o, "y").withColumn("axis", F.lit("y"))).select("axis", "val", "rank")


def y_order(spark, sf_dir):
    o, _ = objects(spark, sf_dir, "ship")
    return number(coords.attach(o, REL["contained"].plan()).select("oid", "y"), ["y", "oid"], "ord").select("oid", F.col("ord").cast("long").alias("ord"))


def entries(spark, sf_dir):
    o, _ = objects(spark, sf_dir)
    return coords.entry_table(coords.attach(o, REL["contained"].plan()).select("oid", "x", "y"))


def generated(kind):
    def run(spark, sf_dir):
        e = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").alias("oid"))
        return synth(e, kind).select("oid", F.col("s").cast("long").alias("s"), F.col("t").cast("long").alias("t"))

    return run


def joined(method):
    def run(spark, sf_dir):
        o, q = objects(spark, sf_dir, "ship")
        return exact.interval_join(o.select("oid", "s", "t"), q.select("qid", "sq", "tq"), REL["overlaps"], method).select("qid", "oid")

    return run


def label_violations(spark, sf_dir):
    o, _ = objects(spark, sf_dir, "ship")
    g = materialize(index.build(o, REL["before"], 8, "practical", 40), "index")
    return audit.broken_labels(g).agg(F.count(F.lit(1)).alias("broken"))


def recall_table(spark, sf_dir):
    o, q = objects(spark, sf_dir)
    g = materialize(index.build(o, REL["overlaps"], 8, "practical", 100), "index")
    r = measure.recall(index.search(g, q, REL["overlaps"], ALL_OF_THEM), exact.filtered_knn(o, q, REL["overlaps"]))
    return r.agg(F.count(F.lit(1)).alias("queries"), F.avg("recall").alias("recall"))


#: Points of a trade-off as lines give them: what is kept of the price stands for recall, the price for speed. In both engines' SQL.
POINTS = """SELECT l_returnflag AS dataset, l_linestatus AS relation, CASE l_linenumber % 3 WHEN 0 THEN 'walk' WHEN 1 THEN 'scan' ELSE 'post' END AS method,
(100 - CAST(round(l_discount * 100) AS BIGINT)) / CAST(100 AS DOUBLE) AS recall, CAST(l_extendedprice AS DOUBLE) AS qps FROM """


def points(spark, sf_dir):
    lines = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    return spark.sql(POINTS + "{lines}", lines=lines)


def frontier(spark, sf_dir):
    return measure.pareto(points(spark, sf_dir), ["dataset", "relation"])


def cube(spark, sf_dir):
    return measure.report(points(spark, sf_dir)).withColumn("recall", F.round("recall", 6))


def events(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/events.parquet")


def session_rows(spark, sf_dir):
    return streams.sessions(events(spark, sf_dir)).select("user_id", F.unix_micros("s").alias("s"), F.unix_micros("t").alias("t"), "n")


def windows(size, slide=None):
    def run(spark, sf_dir):
        w = streams.fixed_intervals(events(spark, sf_dir), size, slide)
        return w.select(F.unix_micros("start").alias("start"), F.unix_micros("end").alias("end"), "n")

    return run


def text_vectors(spark, sf_dir):
    v = vectors.hash_text(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"), "doc_id", "text")
    return v.select("doc_id", F.posexplode("vec").alias("cell", "w")).where("w <> 0").select("doc_id", "cell", F.round("w", 6).alias("w"))


def exact_counts(name, sigma, view="syn"):
    def run(spark, sf_dir):
        o, q = objects(spark, sf_dir, view)
        made, lost = exact_count(o, q.select("qid", "qvec"), REL[name], sigma)
        return made.select("qid", "sq", "tq", F.col("target").cast("long").alias("target"), "realised", "in_bucket").unionByName(lost.select("qid", F.col("target").cast("long").alias("target")), allowMissingColumns=True)

    return run


def sweep_truth(name, sigma, view="syn"):
    def run(spark, sf_dir):
        o, q = objects(spark, sf_dir, view)
        return rounded(exact.filtered_knn(o, exact_count(o, q.select("qid", "qvec"), REL[name], sigma)[0], REL[name]))

    return run


def queries() -> dict:
    q = {f"rel_{r}_{v}": valid_counts(r, v) for r in REL for v in VIEWS}
    q |= {f"filtered_knn_{r}": truth(r) for r in REL} | {"knn_exact": truth(None)}
    q |= {f"slg_search_wide_{r}": graph_search(r, ALL_OF_THEM) for r in REL}
    q |= {"slg_search_wide_sharded": graph_search("contained", ALL_OF_THEM, shard_rows=150, sharding="zone"), "slg_search_wide_conservative": graph_search("overlaps", ALL_OF_THEM, leap="conservative")}
    q |= {"prefilter_knn": truth("contained", how=exact.prefilter), "two_scalar_intersect": truth("overlaps", how=exact.two_scalar)}
    q |= {"postfilter_wide": graph_search("contained", ALL_OF_THEM, mode="post"), "predicate_walk_wide": graph_search("overlaps", ALL_OF_THEM, mode="predicate"), "interval_tree_graphs": tree}
    q |= {"slg_search_ef64": graph_search("overlaps", 64), "slg_exact_build_ef64": graph_search("contained", 64, "exact")}
    q |= {f"slg_no_patch_{p}": graph_search("contained", 64, patch=p) for p in ("none", "previous", "lifetime")} | {"slg_leap_aggressive": graph_search("contained", 64, leap="aggressive")}
    q |= {"snap_states": states, "threshold_lists": threshold_lists, "y_order": y_order, "entry_table": entries, "payload_filter_knn": payload}
    q |= {f"synth_{k}": generated(k) for k in ("uniform", "normal", "skewed", "clustered", "hollow")}
    q |= {f"interval_join_{m}": joined(m) for m in ("broadcast", "dominance", "bucketed")}
    q |= {"label_validity_violations": label_violations, "recall_table": recall_table, "pareto_frontier": frontier, "cube_report": cube}
    q |= {"sessions": session_rows, "tumbling": windows("6 hours"), "sliding": windows("6 hours", "2 hours"), "text_hash_vectors": text_vectors}
    q |= {f"workload_{r}_{tag}": exact_counts(r, sigma) for r, tag, sigma in WORKLOADS}
    q |= {f"sweep_truth_{r}_{tag}": sweep_truth(r, sigma) for r in ("contained", "overlaps") for tag, sigma in SIGMAS.items() if tag != "005"}
    q |= {"workload_contained_price": exact_counts("contained", 0.05, "price"), "workload_overlaps_ship": exact_counts("overlaps", 0.05, "ship")}
    q |= {f"rel_{r}_{v}": valid_counts(r, v) for r in ("contained", "overlaps") for v in WIDE} | {f"filtered_knn_contained_{v}": truth("contained", v) for v in WIDE}
    q |= {f"rel_custom_{tag}": custom_counts(terms) for tag, terms in CUSTOM.items()}
    q |= {"slg_search_scalar_range": scalar_range, "slg_search_custom_swapped": swapped, "slg_search_dates": dated}
    from . import reports, surround

    return q | surround.QUERIES | reports.QUERIES


_OWN = {
    "price": "SELECT l_partkey AS oid, min(l_extendedprice / l_quantity) AS s, max(l_extendedprice / l_quantity) AS t FROM lineitem GROUP BY 1",
    "ship": "SELECT l_orderkey AS oid, min(epoch_us(l_shipdate))::DOUBLE AS s, max(epoch_us(l_shipdate))::DOUBLE AS t FROM lineitem GROUP BY 1",
}


def _draw(seed: str, mod: int) -> str:
    return f"(('0x' || substr(md5('{seed}:' || vec_id::VARCHAR), 1, 8))::BIGINT % {mod})"


def _synth(kind: str) -> str:
    span = 990_000
    u = _draw("start", span)
    start = {
        "uniform": u, "normal": "((" + " + ".join(_draw(f"n{i}", span) for i in range(12)) + ") // 12)", "skewed": f"({u} * ({u} * {u} // {span}) // {span})",
        "clustered": f"least({_draw('c', 10)} * 100000 + 50000 + {_draw('o', 20_000)}, {span})",
        "hollow": f"(CASE WHEN {_draw('side', 2)} = 0 THEN {_draw('h', 300_000)} ELSE {span} - {_draw('h', 300_000)} END)",
    }[kind]
    return f"SELECT vec_id AS oid, {start}::BIGINT AS s, ({start} + {_draw('length', 10_001)})::BIGINT AS t FROM embeddings"


def _vectors(view: str) -> str:
    """(oid, vec, label, s, t) of a view."""
    price = "l_extendedprice / l_quantity"
    if view in ("orders", "partyear"):
        key, at = ("l_orderkey", "epoch_us(l_shipdate)::DOUBLE") if view == "orders" else ("l_partkey * 10 + year(l_shipdate) - 1990", price)
        return f"SELECT {key} AS oid, {features('duckdb')}::DOUBLE[] AS vec, 0 AS label, min({at}) AS s, max({at}) AS t FROM lineitem GROUP BY 1"
    if view == "docs":
        return f"""SELECT v.doc_id AS oid, v.vec, 0 AS label, w.s, w.t FROM (WITH w AS (SELECT doc_id, unnest(regexp_split_to_array(lower(trim(text)), '\\s+')) AS w FROM documents),
c AS (SELECT doc_id, ('0x' || substr(md5(w), 1, 8))::BIGINT % 64 AS cell, count(*) AS n FROM w WHERE w <> '' GROUP BY 1, 2), g AS (SELECT doc_id, range(64) AS cells, map_from_entries(list((cell, n))) AS m, sqrt(sum(n * n)) AS len FROM c GROUP BY 1)
SELECT doc_id, [coalesce(m[x], 0) / len for x in cells]::DOUBLE[] AS vec FROM g) v
JOIN (SELECT row_number() OVER (ORDER BY user_id, s) - 1 AS oid, s::DOUBLE AS s, t::DOUBLE AS t FROM ({_SESSIONS})) w ON w.oid = v.doc_id"""
    own = f"SELECT oid, s::DOUBLE AS s, t::DOUBLE AS t FROM ({_synth('uniform')})" if view == "syn" else _OWN[view]
    return f"SELECT e.vec_id AS oid, e.embedding::DOUBLE[] AS vec, e.label, w.s, w.t FROM embeddings e JOIN ({own}) w ON w.oid = e.vec_id"


def _base(view: str, relation: str = "") -> str:
    pad = "floor((t - s) / 4)" + (" * -1" if relation in ("covers", "before") else "")
    asked = "(SELECT * FROM o WHERE oid % 97 = 7 ORDER BY oid LIMIT 200)" if view in ("orders", "partyear") else "(SELECT * FROM o WHERE oid % 10 = 7)"
    return f"""WITH o AS ({_vectors(view)}), b AS (SELECT * FROM o), q AS (SELECT oid AS qid, vec AS qvec, s - {pad} AS sq, t + {pad} AS tq FROM {asked})
"""


def _workload(name: str, sigma: float, view: str) -> str:
    """made (qid, qvec, sq, tq, target, realised, in_bucket; sq null: unreachable), by the rules of exact_count()."""
    plan = REL[name].plan()
    (a, b), x, y = plan.signs, plan.x, plan.y
    xq = "(CASE WHEN ('0x' || substr(md5('off:' || qid::VARCHAR), 1, 8))::BIGINT % 2 = 0 AND prev IS NOT NULL THEN (xq + prev) / 2 ELSE xq END)"
    ends = {x.query: f"{a} * {xq}", y.query: f"{b} * yq"}
    return _base(view) + f""", xy AS (SELECT {a} * {x.end} AS x, {b} * {y.end} AS y FROM b), m AS (SELECT greatest(1, floor({sigma} * count(*) + 0.5))::BIGINT AS m FROM b),
u AS (SELECT x, lag(x) OVER (ORDER BY x) AS prev, row_number() OVER (ORDER BY x) - 1 AS r, count(*) OVER () AS u FROM (SELECT DISTINCT x FROM xy)),
k AS (SELECT x AS xq, prev, row_number() OVER (ORDER BY x) - 1 AS i, count(*) OVER () AS marks FROM u WHERE r % greatest(1, u // 64) = 0),
f AS (SELECT i, y, row_number() OVER (PARTITION BY i ORDER BY y) AS rn FROM k JOIN xy ON xy.x >= k.xq),
g AS (SELECT i, y AS yq FROM f, m WHERE rn = m), h AS (SELECT g.i, yq, count(*) AS realised FROM g JOIN f ON f.i = g.i AND f.y <= g.yq GROUP BY 1, 2),
d AS (SELECT qid, qvec, t.try, ('0x' || substr(md5(t.try::VARCHAR || ':' || qid::VARCHAR), 1, 8))::BIGINT % (SELECT max(marks) FROM k) AS i FROM q, range(64) t(try)),
e AS (SELECT d.qid, d.qvec, d.try, realised, {ends['sq']} AS sq, {ends['tq']} AS tq FROM d JOIN k ON k.i = d.i JOIN h ON h.i = d.i),
z AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY try) AS rn FROM e WHERE sq <= tq),
made AS (SELECT q.qid, q.qvec, z.sq::DOUBLE AS sq, z.tq::DOUBLE AS tq, m AS target, z.realised, abs(z.realised - m) <= 0.1 * m AS in_bucket FROM m, q LEFT JOIN z ON z.qid = q.qid AND z.rn = 1)
"""


_COND = {n: " AND ".join(f"{t.end} {t.op} {t.query}" for t in r.terms) for n, r in REL.items()}


def _knn(cond: str, view: str = "price", relation: str = "") -> str:
    return _base(view, relation) + _ranked("q", cond)


def _ranked(queries: str, cond: str) -> str:
    return f""", p AS (SELECT qid, oid, list_distance(vec, qvec) AS dist FROM b JOIN {queries} ON {cond}),
r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, oid) AS rank FROM p) SELECT qid, rank, oid, round(dist, 6) AS dist FROM r WHERE rank <= 10"""


def _truth(name: str, sigma: float, view: str) -> str:
    return _workload(name, sigma, view) + _ranked("made", _COND[name])


_SESSIONS = """WITH a AS (SELECT user_id, epoch_us(ts) AS u, lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) AS p FROM events),
g AS (SELECT *, sum(CASE WHEN p IS NULL OR u - p >= 21600000000 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY u) AS g FROM a)
SELECT user_id, min(u) AS s, max(u) AS t, count(*) AS n FROM g GROUP BY user_id, g"""


def oracle_sql() -> dict[str, str]:
    s = {f"rel_{r}_{v}": _base(v, r) + f"SELECT qid, count(oid) AS valid FROM q LEFT JOIN b ON {_COND[r]} GROUP BY qid" for r in REL for v in VIEWS}
    s |= {f"{k}_{r}": _knn(_COND[r], relation=r) for r in REL for k in ("filtered_knn", "slg_search_wide")} | {"knn_exact": _knn("TRUE")}
    s |= {k: _knn(_COND["contained"]) for k in ("prefilter_knn", "postfilter_wide", "interval_tree_graphs", "slg_search_wide_sharded")}
    s |= {k: _knn(_COND["overlaps"]) for k in ("two_scalar_intersect", "predicate_walk_wide", "slg_search_wide_conservative")}
    s["payload_filter_knn"] = _knn(_COND["overlaps"] + " AND label = 3")
    s["snap_states"] = _base("price") + "SELECT qid, (SELECT min(s) FROM b WHERE s >= sq) AS a, (SELECT max(t) FROM b WHERE t <= tq) AS c FROM q"
    s["threshold_lists"] = _base("ship") + "SELECT 'x' AS axis, s AS val, row_number() OVER (ORDER BY s) - 1 AS rank FROM (SELECT DISTINCT s FROM b) UNION ALL SELECT 'y', -t, row_number() OVER (ORDER BY -t) - 1 FROM (SELECT DISTINCT t FROM b)"
    s["y_order"] = _base("ship") + "SELECT oid, row_number() OVER (ORDER BY t, oid) - 1 AS ord FROM b"
    s["entry_table"] = _base("price") + "SELECT oid, s AS x, t AS y FROM (SELECT *, max(s) OVER (ORDER BY t, oid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS m FROM b) WHERE m IS NULL OR s > m"
    s |= {f"synth_{k}": _synth(k) for k in ("uniform", "normal", "skewed", "clustered", "hollow")}
    s |= {f"interval_join_{m}": _base("ship") + f"SELECT qid, oid FROM b JOIN q ON {_COND['overlaps']}" for m in ("broadcast", "dominance", "bucketed")}
    s["label_validity_violations"] = "SELECT 0::BIGINT AS broken"
    s["recall_table"] = _base("price") + f"SELECT count(DISTINCT qid) AS queries, 1.0::DOUBLE AS recall FROM q JOIN b ON {_COND['overlaps']}"
    pts = f"WITH p AS ({POINTS} lineitem) "
    s["pareto_frontier"] = pts + ", m AS (SELECT dataset, relation, recall, max(qps) AS qps FROM p GROUP BY 1, 2, 3), f AS (SELECT * FROM m WHERE NOT EXISTS (SELECT 1 FROM m o WHERE o.dataset = m.dataset AND o.relation = m.relation AND o.recall > m.recall AND o.qps >= m.qps)) SELECT p.* FROM p JOIN f USING (dataset, relation, recall, qps)"
    s["cube_report"] = pts + "SELECT dataset, relation, method, count(*) AS n, round(avg(recall), 6) AS recall FROM p GROUP BY CUBE (dataset, relation, method)"
    s |= {f"workload_{r}_{tag}": _workload(r, sigma, "syn") + "SELECT qid, sq, tq, target, realised, in_bucket FROM made" for r, tag, sigma in WORKLOADS}
    s |= {f"sweep_truth_{r}_{tag}": _truth(r, sigma, "syn") for r in ("contained", "overlaps") for tag, sigma in SIGMAS.items() if tag != "005"}
    s |= {f"workload_{r}_{v}": _workload(r, 0.05, v) + "SELECT qid, sq, tq, target, realised, in_bucket FROM made" for r, v in (("contained", "price"), ("overlaps", "ship"))}
    s |= {f"rel_{r}_{v}": _base(v, r) + f"SELECT qid, count(oid) AS valid FROM q LEFT JOIN b ON {_COND[r]} GROUP BY qid" for r in ("contained", "overlaps") for v in WIDE} | {f"filtered_knn_contained_{v}": _knn(_COND["contained"], v) for v in WIDE}
    wide = ", w AS (SELECT qid, qvec, sq - 100000 AS sq, tq + 100000 AS tq FROM q) "
    cond = lambda terms: " AND ".join(re.sub(r"(>=|<=)", r" \1 ", t) for t in terms)
    s |= {f"rel_custom_{tag}": _base("syn") + wide + f"SELECT qid, count(oid) AS valid FROM w LEFT JOIN b ON {cond(terms)} GROUP BY qid" for tag, terms in CUSTOM.items()}
    s["slg_search_scalar_range"] = _base("syn") + wide + _ranked("w", cond(CUSTOM["start_inside"]))
    s |= {"slg_search_custom_swapped": _knn(_COND["contained"]), "slg_search_dates": _knn(_COND["overlaps"], "ship")}
    s["sessions"] = _SESSIONS
    s["tumbling"] = "SELECT epoch_us(ts) // 21600000000 * 21600000000 AS start, epoch_us(ts) // 21600000000 * 21600000000 + 21600000000 AS \"end\", count(*) AS n FROM events GROUP BY 1, 2"
    s["sliding"] = "WITH x AS (SELECT epoch_us(ts) // 7200000000 * 7200000000 - k * 7200000000 AS start FROM events, range(3) r(k)) SELECT start, start + 21600000000 AS \"end\", count(*) AS n FROM x GROUP BY 1, 2"
    s["text_hash_vectors"] = """WITH w AS (SELECT doc_id, unnest(regexp_split_to_array(lower(trim(text)), '\\s+')) AS w FROM documents),
c AS (SELECT doc_id, (('0x' || substr(md5(w), 1, 8))::BIGINT % 64)::INTEGER AS cell, count(*) AS n FROM w WHERE w <> '' GROUP BY 1, 2)
SELECT doc_id, cell, round(n / sqrt(sum(n * n) OVER (PARTITION BY doc_id)), 6) AS w FROM c"""
    from . import reports, surround

    return s | surround.sql(_base, _ranked, _COND, pts) | reports.sql(_workload)
