"""Driver queries for the operators around the search: joins, statistics, windows, payloads, formats, sampling, SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..functions import coords, relations
from ..operators import exact, index, joins, measure, stats
from ..session import materialize, number, shared_dir
from ..sources import tables
from . import sqlapi
from .workload import MICROS, objects

REL = relations.ALL


def _axes(spark, sf_dir, view="syn", name="contained"):
    o, q = objects(spark, sf_dir, view)
    plan = REL[name].plan()
    return coords.attach(o, plan), coords.attach_queries(q, plan)


def rounded(df):
    return df.select("qid", F.col("rank").cast("long").alias("rank"), "oid", F.round("dist", 6).alias("dist"))


def prefix_knn(spark, sf_dir):
    o, _ = _axes(spark, sf_dir)
    return rounded(joins.prefix_knn(number(o.select("oid", "vec", "y"), ["y", "oid"], "ord"), 5, 128))


def knn_join(spark, sf_dir):
    e = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").alias("oid"), F.col("embedding").alias("vec"))
    q = e.where("oid % 50 = 0").select(F.col("oid").alias("qid"), F.col("vec").alias("qvec"), F.lit(5).alias("k"))
    return rounded(exact.top(joins.knn_join(q, e, 5).join(q.select("qid", "k"), "qid")))


def asof(direction):
    def run(spark, sf_dir):
        """For each event of one kind, the time of the user-independent next, or last, purchase."""
        e = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "event_type", F.expr(MICROS.format("ts")).cast("double").alias("u"))
        kinds = e.agg(F.min("event_type"), F.max("event_type")).first()
        left, right = (e.where(F.col("event_type") == k) for k in kinds)
        return joins.asof(left.select("event_id", "u"), right.select("u"), "u", "u", direction).select("event_id", F.col("found").cast("long").alias("found"))

    return run


def sigma_bounds(spark, sf_dir):
    o, q = _axes(spark, sf_dir)
    counts, frame = stats.grid(o.select("x", "y"), 16)
    return stats.bounds(q, counts, frame, 16).select("qid", F.col("low").cast("long").alias("low"), F.col("high").cast("long").alias("high"))


def planner_choice(spark, sf_dir):
    o, q = _axes(spark, sf_dir)
    counts, frame = stats.grid(o.select("x", "y"), 16)
    return stats.choose(stats.bounds(q, counts, frame, 16), 5)


def planned_search(spark, sf_dir):
    o, q = objects(spark, sf_dir)
    shards = materialize(index.pack(index.build(o, REL["contained"], 8, "practical", 100)), "packed")
    return rounded(sqlapi.planned(o, shards, q, REL["contained"], 100, 1 << 20)[0])


def local_density(spark, sf_dir):
    o, _ = _axes(spark, sf_dir)
    return stats.density(o, 20_000.0)


def state_counts(spark, sf_dir):
    o, _ = _axes(spark, sf_dir, "ship", "after")
    s = stats.states(o)
    near = lambda a, b: F.abs(F.col(a) - F.col(b)) <= 0.1 * F.col(b)
    return s.select("xs", "ys", (near("about_xs", "xs") & near("about_ys", "ys")).alias("sketch_is_near"))


def threshold_successors(spark, sf_dir):
    o, _ = _axes(spark, sf_dir, "ship")
    return stats.successors(coords.thresholds(o, "x"))


def prefix_blocks(spark, sf_dir):
    """Eight blocks of the Y order, near equal."""
    o, _ = _axes(spark, sf_dir)
    n = o.count()
    return number(o.select("oid", "y"), ["y", "oid"], "ord").select("oid", F.floor(F.col("ord") * 8 / n).cast("long").alias("block"))


def valid_except(spark, sf_dir):
    o, q = objects(spark, sf_dir, "ship")
    pairs = lambda r: exact.interval_join(o.select("oid", "s", "t"), q.select("qid", "sq", "tq"), REL[r], "dominance")
    return pairs("overlaps").exceptAll(pairs("contained"))


def never_valid(spark, sf_dir):
    """Objects that no query finds valid (anti join), and how many any does (semi join)."""
    o, q = objects(spark, sf_dir, "ship")
    hit = exact.interval_join(o.select("oid", "s", "t"), q.select("qid", "sq", "tq"), REL["contained"], "dominance")
    return joins.anti(o.select("oid"), hit, ["oid"]).withColumn("valid", F.lit(False)).union(joins.semi(o.select("oid"), hit, ["oid"]).withColumn("valid", F.lit(True)))


def interval_of_groups(spark, sf_dir):
    ls = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    at = F.expr(MICROS.format("l_shipdate"))
    return ls.groupBy(F.col("l_suppkey").alias("oid")).agg(F.min(at).alias("s"), F.max(at).alias("t"), F.max_by("l_orderkey", F.struct(at, "l_orderkey", "l_linenumber")).alias("last_order"))


def month_overlap(spark, sf_dir):
    """For each month in which something was ordered, the orders whose ship dates overlap it."""
    lines = spark.read.parquet(f"{sf_dir}/lineitem.parquet").groupBy(F.col("l_orderkey").alias("oid")).agg(F.min(F.expr(MICROS.format("l_shipdate")).cast("double")).alias("s"), F.max(F.expr(MICROS.format("l_shipdate")).cast("double")).alias("t"))
    a, b = tables.month("o_orderdate")
    months = spark.read.parquet(f"{sf_dir}/orders.parquet").select(a.alias("sq"), b.alias("tq")).distinct().withColumn("qid", F.col("sq").cast("long"))
    return measure.selectivity(lines, months, REL["overlaps"]).select("qid", "valid")


def json_payload(spark, sf_dir):
    e = tables.props(spark.read.parquet(f"{sf_dir}/events.parquet"))
    return e.groupBy("event_type").agg(F.count("k").alias("n"), F.sum("k").alias("total"), F.max("k").alias("most"))


def page_payload(spark, sf_dir):
    p = spark.read.parquet(f"{sf_dir}/pages.parquet")
    return p.select("page_id", tables.host("url").alias("host"), F.length(tables.page_text("html")).cast("long").alias("chars"))


def sampled(spark, sf_dir):
    return tables.sample(spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_orderkey", "o_orderstatus"), "o_orderkey", 10)


def formats(spark, sf_dir):
    o, _ = objects(spark, sf_dir, "syn")
    at = f"{shared_dir(spark)}/intervals-{uuid.uuid4().hex}"
    out = None
    for kind in ("csv", "json", "orc", "parquet"):
        tables.write_intervals(o, f"{at}/{kind}", kind)
        one = tables.read_intervals(spark, f"{at}/{kind}", kind).agg(F.count(F.lit(1)).alias("n"), F.sum("s").alias("s"), F.sum("t").alias("t")).withColumn("kind", F.lit(kind))
        out = one if out is None else out.union(one)
    return out


def written_results(spark, sf_dir):
    o, q = objects(spark, sf_dir)
    at = f"{shared_dir(spark)}/results-{uuid.uuid4().hex}"
    tables.write_results(rounded(exact.filtered_knn(o, q, REL["contained"])), at)
    return spark.read.parquet(at)


def stored_index(spark, sf_dir):
    """Saved, loaded, and searched by what the store says of itself."""
    o, q = objects(spark, sf_dir)
    at = f"{shared_dir(spark)}/store-{uuid.uuid4().hex}"
    index.save(index.build(o, REL["overlaps"], 8, "practical", 100, shard_rows=200), at, REL["overlaps"], m=8)
    held, relation, _ = index.load(spark, at)
    return rounded(index.search(held["shards"], q, relation, 1 << 20))


def stored_entries(spark, sf_dir):
    o, _ = objects(spark, sf_dir)
    at = f"{shared_dir(spark)}/store-{uuid.uuid4().hex}"
    index.save(index.build(o, REL["contained"], 4, "practical", 20, shard_rows=1 << 30), at, REL["contained"])
    return index.load(spark, at)[0]["entries"].select("oid", "x", "y")


def layered(spark, sf_dir):
    from ..operators import interval_tree

    o, q = objects(spark, sf_dir)
    return rounded(interval_tree.search_layered(interval_tree.build_layered(o, REL["contained"], 8, 100), q, REL["contained"], 1 << 20))


def labelled_edges_hold(spark, sf_dir):
    """Edges of the exact graph whose label lets in an invalid end, by O9's test on every edge: none."""
    from ..operators import audit

    o, _ = objects(spark, sf_dir, "syn")
    g = materialize(index.build(o.where("oid < 200"), REL["overlaps"], 6, "exact"), "index")
    return audit.broken_labels(g).agg(F.count(F.lit(1)).alias("broken")).withColumn("parts", F.lit(0).cast("long") + audit.unconnected(g, 0, g.agg(F.max("yr")).first()[0]))


def _nearest(o, q, name):
    """qid, oid: the ten nearest valid objects of each query and batch of objects, chosen by matrix products. The nearest of all are among them."""
    o, q = coords.on_axis(o, "s", "t"), coords.on_axis(q, "sq", "tq")
    return joins.knn_join(q, o, 10, lambda asked, held: exact._meets(REL[name].terms, asked, held), exact.ENDS).select("qid", "oid")


def sql_functions(spark, sf_dir):
    """The functions judge and measure, in SQL, what matrix products leave of all pairs."""
    sqlapi.register(spark)
    o, q = objects(spark, sf_dir)
    o.select("oid", "s", "t", F.transform("vec", lambda x: x.cast("double")).alias("vec")).createOrReplaceTempView("iv_objects")
    q.select("qid", "sq", "tq", F.transform("qvec", lambda x: x.cast("double")).alias("qvec")).createOrReplaceTempView("iv_queries")
    materialize(_nearest(o, q, "overlaps"), "near").createOrReplaceTempView("iv_near")
    return spark.sql("""SELECT qid, CAST(rank AS BIGINT) AS rank, oid, round(dist, 6) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, oid) AS rank FROM
        (SELECT qid, oid, iv_l2(vec, qvec) AS dist FROM iv_near JOIN iv_objects USING (oid) JOIN iv_queries USING (qid) WHERE iv_overlaps(s, t, sq, tq))) WHERE rank <= 10""")


def sql_topk(spark, sf_dir):
    o, q = objects(spark, sf_dir)
    from ..functions.vectors import l2

    near = materialize(_nearest(o, q, "contained"), "near")
    pairs = near.join(o, "oid").join(q, "qid").select("qid", "oid", l2("vec", "qvec").alias("dist"))
    return rounded(sqlapi.topk_by(pairs, "qid", "dist", "oid", 10))


def sql_table_function(spark, sf_dir):
    """Blocks of queries meet each shard by a lateral call; SQL merges the shards' answers."""
    o, q = objects(spark, sf_dir)
    materialize(index.pack(index.build(o, REL["contained"], 8, "practical", 100)), "packed").createOrReplaceTempView("iv_shards")
    sqlapi.interval_knn_blocks(spark, REL["contained"])
    held = materialize(q.select("qid", F.transform("qvec", lambda x: x.cast("double")).alias("qvec"), "sq", "tq"), "asked")
    n = max(1, -(-held.count() // 2048))
    one = held.withColumn("block", F.pmod(F.xxhash64("qid"), F.lit(n))).groupBy("block").agg(F.collect_list(F.struct("qid", "qvec", "sq", "tq")).alias("r"))
    materialize(one.select(*[F.col(f"r.{c}").alias(f"{c}s") for c in ("qid", "qvec", "sq", "tq")]), "blocks").createOrReplaceTempView("iv_blocks")
    return spark.sql("""SELECT qid, oid, round(dist, 6) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, oid) AS rank FROM
        (SELECT f.* FROM (SELECT /*+ REPARTITION(64) */ * FROM iv_shards CROSS JOIN iv_blocks), LATERAL interval_knn_blocks(blob, qids, qvecs, sqs, tqs, 10, 100000) f)) WHERE rank <= 10""")


TEXT = "SELECT oid FROM (SELECT oid, iv_l2(vec, :q) AS dist FROM iv_all WHERE iv_overlaps(s, t, :a, :b)) ORDER BY dist, oid LIMIT :k"


def sql_text(spark, sf_dir):
    """One query as text, answered once as written and once from an index."""
    sqlapi.register(spark)
    o, q = objects(spark, sf_dir)
    o = o.withColumn("vec", F.transform("vec", lambda x: x.cast("double")))
    o.createOrReplaceTempView("iv_all")
    r = q.orderBy("qid").first()
    args = {"a": r.sq, "b": r.tq, "q": [float(x) for x in r.qvec], "k": 10}
    shards = materialize(index.pack(index.build(o, REL["overlaps"], 8, "practical", 100)), "packed")
    plain, held = sqlapi.sql(spark, TEXT, args), sqlapi.sql(spark, TEXT, args, {("iv_all", "overlaps"): shards}, 1 << 20)
    return plain.withColumn("how", F.lit("scan")).union(held.withColumn("how", F.lit("index")))


def subqueries(spark, sf_dir):
    """Correlated exists and a scalar maximum: objects that some query finds valid and that start latest of their label."""
    o, q = objects(spark, sf_dir, "price")
    o.select("oid", "s", "t").createOrReplaceTempView("iv_plain")
    q.select("qid", "sq", "tq").createOrReplaceTempView("iv_asking")
    return spark.sql("SELECT oid, (SELECT max(s) FROM iv_plain) - s AS behind FROM iv_plain o WHERE EXISTS (SELECT 1 FROM iv_asking q WHERE o.s >= q.sq AND o.t <= q.tq)").select("oid", F.round("behind", 6).alias("behind"))


def outside_class(spark, sf_dir):
    """A strict comparison is out of the class: the exact filter answers."""
    o, q = objects(spark, sf_dir)
    return rounded(sqlapi.outside(["s>sq", "t<=tq"], o, q, (F.col("s") > F.col("sq")) & (F.col("t") <= F.col("tq"))))


def appended(spark, sf_dir):
    """Batches in Y order go to the open shard, late ones to the delta; together they answer as one index does."""
    from ..streaming.append import Appender

    o, q = objects(spark, sf_dir, "syn")
    a = Appender(spark, REL["contained"], f"{shared_dir(spark)}/append-{uuid.uuid4().hex}", m=8, pool=100)
    late = F.col("oid") % 17 == 0
    for i in range(3):
        a.add(o.where(~late & (F.floor(F.col("t") / 340_000) == i)), i)
    a.add(o.where(late), 3)
    a.add(o.where(late), 3)  # a batch that is delivered again counts once
    return rounded(a.search(q, 1 << 20))


def rollup(spark, sf_dir):
    from .queries import points

    return points(spark, sf_dir).rollup("dataset", "method").agg(F.count(F.lit(1)).alias("n"), F.max("qps").alias("qps"))


def grouping_sets(spark, sf_dir):
    from .queries import points

    points(spark, sf_dir).createOrReplaceTempView("iv_points")
    return spark.sql("SELECT relation, method, count(*) AS n, round(avg(recall), 6) AS recall FROM iv_points GROUP BY GROUPING SETS ((relation), (method), ())")


def pivoted(spark, sf_dir):
    from .queries import points

    best = points(spark, sf_dir).groupBy("dataset", "relation", "method").agg(F.max("recall").alias("recall")).withColumn("sigma", F.lit(0.1))
    return measure.by_method(best)


def best_at(spark, sf_dir):
    from .queries import points

    p = points(spark, sf_dir).withColumn("params", F.col("recall").cast("string"))
    return measure.qps_at(p, 0.94, ["dataset", "method"]).select("dataset", "method", "qps")


def normalised(spark, sf_dir):
    from .queries import points

    p = points(spark, sf_dir).select("relation", F.lit(0.1).alias("sigma"), F.col("method").alias("distribution"), "qps").groupBy("relation", "sigma", "distribution").agg(F.max("qps").alias("qps"))
    return measure.normalised(p, "walk").select("distribution", "ratio")


QUERIES = {
    "prefix_knn_join": prefix_knn, "knn_join": knn_join, "asof_forward": asof("forward"), "asof_backward": asof("backward"), "sigma_bounds": sigma_bounds, "planner_choice": planner_choice, "planned_search": planned_search,
    "local_density": local_density, "state_counts": state_counts, "threshold_successors": threshold_successors, "prefix_blocks": prefix_blocks, "valid_except": valid_except, "never_valid": never_valid,
    "interval_of_groups": interval_of_groups, "month_overlap": month_overlap, "json_payload": json_payload, "page_payload": page_payload, "md5_sample": sampled, "interval_formats": formats, "written_results": written_results,
    "stored_index": stored_index, "stored_entries": stored_entries, "layered_graph": layered, "label_tests": labelled_edges_hold, "sql_functions": sql_functions, "sql_topk_by": sql_topk, "sql_table_function": sql_table_function,
    "sql_text": sql_text, "sql_subqueries": subqueries, "outside_class": outside_class, "appended_shards": appended, "report_rollup": rollup, "report_grouping_sets": grouping_sets, "report_pivot": pivoted, "qps_at_recall": best_at, "qps_normalised": normalised,
}


def sql(base, ranked, cond, points) -> dict[str, str]:
    """The same in DuckDB; base, ranked and cond are the parts that all searches share."""
    own = lambda c, t="": base("price") + ranked("q", cond[c] + t)
    syn = base("syn")
    cells = """, g AS (SELECT min(s) AS x0, CASE WHEN max(s) = min(s) THEN 1 ELSE (max(s) - min(s)) / 16 END AS w, min(t) AS y0, CASE WHEN max(t) = min(t) THEN 1 ELSE (max(t) - min(t)) / 16 END AS h FROM b),
n AS (SELECT least(floor((s - x0) / w), 15) AS i, least(floor((t - y0) / h), 15) AS j, count(*) AS n FROM b, g GROUP BY 1, 2),
a AS (SELECT qid, least(greatest(floor((sq - x0) / w), -1), 16) AS qi, least(greatest(floor((tq - y0) / h), -1), 16) AS qj FROM q, g),
e AS (SELECT qid, coalesce(sum(CASE WHEN i > qi AND j < qj THEN n END), 0)::BIGINT AS low, coalesce(sum(n), 0)::BIGINT AS high FROM a LEFT JOIN n ON i >= least(qi, 15) AND j <= qj AND qi <= 16 GROUP BY qid) """
    asof = lambda agg, op: f"""WITH k AS (SELECT min(event_type) AS a, max(event_type) AS b FROM events), l AS (SELECT event_id, epoch_us(ts) AS u FROM events, k WHERE event_type = a), r AS (SELECT epoch_us(ts) AS v FROM events, k WHERE event_type = b)
SELECT event_id, (SELECT {agg}(v) FROM r WHERE v {op} u) AS found FROM l"""  # noqa: E731
    ship = base("ship")
    return {
        "prefix_knn_join": syn + ", p AS (SELECT x.oid AS qid, y.oid, list_distance(x.vec, y.vec) AS dist FROM b x JOIN b y ON (y.t, y.oid) < (x.t, x.oid)), r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, oid) AS rank FROM p) SELECT qid, rank, oid, round(dist, 6) AS dist FROM r WHERE rank <= 5",
        "knn_join": "WITH e AS (SELECT vec_id AS oid, embedding::DOUBLE[] AS vec FROM embeddings), p AS (SELECT q.oid AS qid, e.oid, list_distance(q.vec, e.vec) AS dist FROM e, e q WHERE q.oid % 50 = 0), r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, oid) AS rank FROM p) SELECT qid, rank, oid, round(dist, 6) AS dist FROM r WHERE rank <= 5",
        "asof_forward": asof("min", ">="), "asof_backward": asof("max", "<="),
        "sigma_bounds": syn + cells + "SELECT * FROM e", "planner_choice": syn + cells + "SELECT qid, CASE WHEN high = 0 THEN 'empty' WHEN high <= 5 THEN 'scan' ELSE 'walk' END AS how FROM e",
        "planned_search": own("contained"), "written_results": own("contained"), "stored_index": own("overlaps"), "layered_graph": own("contained"), "sql_functions": own("overlaps"), "sql_topk_by": own("contained"),
        "local_density": syn + "SELECT oid, count(*) OVER (ORDER BY t RANGE BETWEEN 20000 PRECEDING AND CURRENT ROW) AS n FROM b",
        "state_counts": ship + "SELECT count(DISTINCT s) AS xs, count(DISTINCT t) AS ys, TRUE AS sketch_is_near FROM b",
        "threshold_successors": ship + "SELECT s AS val, lead(s) OVER (ORDER BY s) AS next FROM (SELECT DISTINCT s FROM b)",
        "prefix_blocks": syn + "SELECT oid, floor((row_number() OVER (ORDER BY t, oid) - 1) * 8 / count(*) OVER ())::BIGINT AS block FROM b",
        "valid_except": ship + f"SELECT qid, oid FROM b JOIN q ON {cond['overlaps']} EXCEPT ALL SELECT qid, oid FROM b JOIN q ON {cond['contained']}",
        "never_valid": ship + f"SELECT oid, EXISTS (SELECT 1 FROM q WHERE {cond['contained']}) AS valid FROM b",
        "interval_of_groups": "SELECT l_suppkey AS oid, min(epoch_us(l_shipdate)) AS s, max(epoch_us(l_shipdate)) AS t, arg_max(l_orderkey, (epoch_us(l_shipdate), l_orderkey, l_linenumber)) AS last_order FROM lineitem GROUP BY 1",
        "month_overlap": "WITH m AS (SELECT DISTINCT date_trunc('month', o_orderdate) AS m FROM orders), o AS (SELECT l_orderkey, min(epoch_us(l_shipdate)) AS s, max(epoch_us(l_shipdate)) AS t FROM lineitem GROUP BY 1) SELECT epoch_us(m::TIMESTAMP) AS qid, count(l_orderkey) AS valid FROM m LEFT JOIN o ON t >= epoch_us(m::TIMESTAMP) AND s <= epoch_us((m + INTERVAL 1 MONTH)::TIMESTAMP) - 1 GROUP BY 1",
        "json_payload": "SELECT event_type, count(k) AS n, sum(k)::BIGINT AS total, max(k) AS most FROM (SELECT event_type, json_extract(props, '$.k')::BIGINT AS k FROM events) GROUP BY 1",
        "page_payload": r"SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, length(trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[ \t\n\r]+', ' ', 'g'))) AS chars FROM pages",
        "md5_sample": "SELECT o_orderkey, o_orderstatus FROM orders WHERE ('0x' || substr(md5('sample:' || o_orderkey::VARCHAR), 1, 8))::BIGINT % 10 = 0",
        "interval_formats": syn + "SELECT n, s, t, kind FROM (SELECT count(*) AS n, sum(s) AS s, sum(t) AS t FROM b), (VALUES ('csv'), ('json'), ('orc'), ('parquet')) v(kind)",
        "stored_entries": base("price") + "SELECT oid, s AS x, t AS y FROM (SELECT *, max(s) OVER (ORDER BY t, oid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS m FROM b) WHERE m IS NULL OR s > m",
        "label_tests": "SELECT 0::BIGINT AS broken, 0::BIGINT AS parts",
        "sql_table_function": base("price") + f", p AS (SELECT qid, oid, list_distance(vec, qvec) AS dist FROM b JOIN q ON {cond['contained']}), r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, oid) AS rank FROM p) SELECT qid, oid, round(dist, 6) AS dist FROM r WHERE rank <= 10",
        "sql_text": base("price") + f", f AS (SELECT oid FROM b JOIN (SELECT * FROM q ORDER BY qid LIMIT 1) ON {cond['overlaps']} ORDER BY list_distance(vec, qvec), oid LIMIT 10) SELECT oid, how FROM f, (VALUES ('scan'), ('index')) v(how)",
        "sql_subqueries": base("price") + f"SELECT oid, round((SELECT max(s) FROM b) - s, 6) AS behind FROM b WHERE EXISTS (SELECT 1 FROM q WHERE {cond['contained']})",
        "outside_class": base("price") + ranked("q", "s > sq AND t <= tq"),
        "appended_shards": syn + ranked("q", cond["contained"]),
        "report_rollup": points + "SELECT dataset, method, count(*) AS n, max(qps) AS qps FROM p GROUP BY ROLLUP (dataset, method)",
        "report_grouping_sets": points + "SELECT relation, method, count(*) AS n, round(avg(recall), 6) AS recall FROM p GROUP BY GROUPING SETS ((relation), (method), ())",
        "report_pivot": points + "SELECT dataset, relation, 0.1::DOUBLE AS sigma, max(CASE WHEN method = 'post' THEN recall END) AS post, max(CASE WHEN method = 'scan' THEN recall END) AS scan, max(CASE WHEN method = 'walk' THEN recall END) AS walk FROM p GROUP BY 1, 2",
        "qps_at_recall": points + "SELECT dataset, method, max(qps) AS qps FROM p WHERE recall >= 0.94 GROUP BY 1, 2",
        "qps_normalised": points + "SELECT method AS distribution, qps / max(CASE WHEN method = 'walk' THEN qps END) OVER (PARTITION BY relation) AS ratio FROM (SELECT relation, method, max(qps) AS qps FROM p GROUP BY 1, 2)",
    }
