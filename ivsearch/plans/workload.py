"""Objects and queries of the experiments, from the given tables; all draws are md5 integers, equal in any engine."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.coords import attach, thresholds
from ..functions.relations import Relation
from ..functions.vectors import hash_text
from ..operators.joins import cell_of, cuts_of
from ..session import materialize, number

T = 1_000_000


def draw(seed: str, key, mod: int) -> Column:
    h = F.md5(F.concat(F.lit(f"{seed}:"), F.col(key).cast("string")))
    return F.conv(F.substring(h, 1, 8), 16, 10).cast("long") % mod


def synth(ids: DataFrame, kind: str = "uniform", key: str = "oid", top: int = T, longest: float = 0.01) -> DataFrame:
    """ids with s and t (double): starts by a distribution, lengths uniform up to longest * top.

    uniform; normal: the mean of twelve draws; skewed: the cube of a draw; clustered: ten centres and a small offset; hollow: the outer 30% at either end.
    """
    cap = int(longest * top)
    u = draw("start", key, top - cap)
    span = F.lit(top - cap)
    start = {
        "uniform": u,
        "normal": F.floor(sum((draw(f"n{i}", key, top - cap) for i in range(12)), F.lit(0)) / 12).cast("long"),
        "skewed": F.floor(u * F.floor(u * u / span) / span).cast("long"),
        "clustered": F.least((draw("c", key, 10) * (top // 10) + top // 20 + draw("o", key, top // 50)), span.cast("long")),
        "hollow": F.when(draw("side", key, 2) == 0, draw("h", key, top * 3 // 10)).otherwise(span - draw("h", key, top * 3 // 10)),
    }[kind]
    return ids.withColumn("s", start.cast("double")).withColumn("t", (start + draw("length", key, cap + 1)).cast("double"))


MICROS = "timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', {})"
#: Twelve numbers of a group of lines, all sums of whole numbers, so that any engine gives the same.
FEATURES = "[count(*) / 1.0, sum({q}) / 10.0, min({q}) / 5.0, max({q}) / 5.0, sum({p}) / 1e6, min({p}) / 1e5, max({p}) / 1e5, sum({d}) / 10.0, max({d}) / 1.0, sum({t}) / 10.0, max({t}) / 1.0, count(DISTINCT l_returnflag) / 1.0]"


def features(engine: str) -> str:
    whole = lambda c, by: f"CAST(round({c} * {by}) AS BIGINT)"
    text = FEATURES.format(q=whole("l_quantity", 1), p=whole("l_extendedprice", 100), d=whole("l_discount", 100), t=whole("l_tax", 100))
    return f"array({text[1:-1]})" if engine == "spark" else text


def objects(spark: SparkSession, sf_dir: str, view: str = "price", relation: str = "", kind: str = "uniform") -> tuple[DataFrame, DataFrame]:
    """(objects, queries) of a view.

    price: vectors with the least and largest unit price of the part's lines; ship: with the first and last ship date of the order's lines, in microseconds;
    syn: with generated intervals of a kind; docs: hashed texts with the sessions of the event stream, by their places in either order;
    orders: twelve features of an order's lines and their ship dates; partyear: the same of a part's lines in a year, and their unit prices.
    Queries carry their own object's interval, widened by a quarter on both sides, as [sq, tq]; for covers and before, narrowed.
    All rows are objects. The stated queries are those with oid % 10 = 7 (orders and partyear: the 200 smallest with oid % 97 = 7), so each also finds itself.
    """
    read = lambda t: spark.read.parquet(f"{sf_dir}/{t}.parquet")
    e = lambda: read("embeddings").select(F.col("vec_id").alias("oid"), F.col("embedding").alias("vec"))
    price = F.col("l_extendedprice") / F.col("l_quantity")
    if view == "syn":
        rows = synth(e(), kind)
    elif view == "price":
        rows = e().join(read("lineitem").groupBy(F.col("l_partkey").alias("oid")).agg(F.min(price).alias("s"), F.max(price).alias("t")), "oid")
    elif view == "ship":
        micros = F.expr(MICROS.format("l_shipdate")).cast("double")
        rows = e().join(read("lineitem").groupBy(F.col("l_orderkey").alias("oid")).agg(F.min(micros).alias("s"), F.max(micros).alias("t")), "oid")
    elif view == "docs":
        from ..streaming.sessions import sessions

        spans = sessions(read("events")).select("user_id", F.unix_micros("s").cast("double").alias("s"), F.unix_micros("t").cast("double").alias("t"))
        placed = number(spans, ["user_id", "s"], "place").select(F.col("place").alias("oid"), "s", "t")
        rows = hash_text(read("documents").select("doc_id", "text"), "doc_id", "text").withColumnRenamed("doc_id", "oid").join(placed, "oid")
    else:
        micros, year = F.expr(MICROS.format("l_shipdate")).cast("double"), F.year("l_shipdate")
        key, at = (F.col("l_orderkey"), micros) if view == "orders" else (F.col("l_partkey") * 10 + year - 1990, price)
        rows = read("lineitem").groupBy(key.alias("oid")).agg(F.expr(features("spark")).alias("vec"), F.min(at).alias("s"), F.max(at).alias("t"))
        rows = rows.select("oid", F.transform("vec", lambda x: x.cast("double")).alias("vec"), "s", "t")
    pad = F.floor((F.col("t") - F.col("s")) / 4) * (-1 if relation in ("covers", "before") else 1)
    asked = rows.where("oid % 97 = 7").orderBy("oid").limit(200) if view in ("orders", "partyear") else rows.where("oid % 10 = 7")
    q = asked.select(F.col("oid").alias("qid"), F.col("vec").alias("qvec"), (F.col("s") - pad).alias("sq"), (F.col("t") + pad).alias("tq"), F.lit(10).alias("k"))
    return rows, q


def exact_count(objs: DataFrame, qvectors: DataFrame, relation: Relation, sigma: float, k: int = 10, tries: int = 64, marks: int = 64) -> tuple[DataFrame, DataFrame]:
    """(queries, unreachable): queries (qid, qvec, sq, tq, k, target, realised, in_bucket) whose valid sets hold target = sigma * n objects, up to ties in Y, and (qid, target) of those for which no draw gives an interval.

    Every so many-th threshold of X is a mark. For a mark with enough objects at or above it the y bound is the target-th smallest Y among them.
    Each query draws marks until one gives sq <= tq. Half of the queries get an x between two thresholds, which leaves their valid set as it is. in_bucket: realised is within a tenth of the target.

    Two passes over the objects: counts by mark and range of Y, which tell for each mark the range that holds its bound; then
    an order within those ranges. What is gathered is marks * ranges numbers. No object meets more marks than share a range.
    """
    spark, plan = objs.sparkSession, relation.plan()
    data = attach(objs, plan).select("oid", "x", "y")
    n = data.count()
    m = max(1, int(np.floor(sigma * n + 0.5)))
    ux = materialize(thresholds(data, "x"), "ux")
    step = max(1, ux.count() // marks)
    before = ux.select((F.col("rank") + 1).alias("rank"), F.col("val").alias("prev"))
    xs = sorted(ux.where(F.col("rank") % step == 0).join(before, "rank", "left").select("rank", "val", "prev").collect())  # at most 2 * marks
    none = qvectors.select("qid", F.lit(m).alias("target"))
    if not xs:
        shape = qvectors.select("qid", "qvec", *(F.lit(0.0).alias(c) for c in ("sq", "tq")), F.lit(k).alias("k"), F.lit(m).alias("target"), F.lit(0).cast("long").alias("realised"), F.lit(True).alias("in_bucket"))
        return shape.limit(0), none
    cuts = cuts_of(data, "y", 256)
    placed = data.select("y", cell_of(F.col("x"), [r.val for r in xs]).alias("c"), cell_of(F.col("y"), cuts).alias("z"))
    table = np.zeros((len(xs) + 1, len(cuts) + 1), np.int64)
    for r in placed.groupBy("c", "z").count().collect():
        table[r.c, r.z] = r["count"]
    upto = np.cumsum(np.cumsum(table[::-1], 0)[::-1], 1)  # [c, z]: objects at mark c or above, in ranges up to z
    wanted = []
    for i in range(len(xs)):
        own = upto[i + 1]
        if own[-1] >= m:
            z = int(np.searchsorted(own, m))
            wanted.append((i, z, int(own[z - 1]) if z else 0))
    if not wanted:
        return exact_count(objs.limit(0), qvectors, relation, sigma, k)[0], none
    marked = spark.createDataFrame([(i, z, b, float(xs[i].val), None if xs[i].prev is None else float(xs[i].prev)) for i, z, b in wanted], "i int, z int, earlier long, xq double, prev double")
    near = placed.join(F.broadcast(marked), "z").where(F.col("c") > F.col("i"))
    by = W.partitionBy("i")
    ranked = near.withColumn("r", F.row_number().over(by.orderBy("y"))).withColumn("ties", F.max("r").over(W.partitionBy("i", "y")))
    bound = materialize(ranked.where(F.col("r") + F.col("earlier") == m).select("i", "xq", "prev", F.col("y").alias("yq"), (F.col("earlier") + F.col("ties")).alias("realised")), "marks")
    a, b = plan.signs
    asked = qvectors.select("qid", "qvec").withColumn("try", F.explode(F.sequence(F.lit(0), F.lit(tries - 1))))
    pick = F.conv(F.substring(F.md5(F.concat_ws(":", "try", "qid")), 1, 8), 16, 10).cast("long") % len(xs)
    between = (draw("off", "qid", 2) == 0) & F.col("prev").isNotNull()
    xq = F.when(between, (F.col("xq") + F.col("prev")) / 2).otherwise(F.col("xq"))
    ends = {plan.x.query: xq * a, plan.y.query: F.col("yq") * b}
    if len(ends) < 2:
        raise ValueError("both terms bound the same end of the query")
    made = asked.withColumn("i", pick.cast("int")).join(F.broadcast(bound), "i").select("qid", "qvec", "try", "realised", ends["sq"].alias("sq"), ends["tq"].alias("tq")).where("sq <= tq")
    first = made.withColumn("r", F.row_number().over(W.partitionBy("qid").orderBy("try"))).where("r = 1")
    out = materialize(first.select("qid", "qvec", "sq", "tq", F.lit(k).alias("k"), F.lit(m).alias("target"), "realised", (F.abs(F.col("realised") - m) <= 0.1 * m).alias("in_bucket")), "workload")
    return out, none.join(out.select("qid"), "qid", "left_anti")
