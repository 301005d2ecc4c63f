"""Exact answers: filtered and unfiltered k nearest neighbours, interval joins, and baselines built from them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.coords import attach, attach_queries, on_axis
from ..functions.relations import Relation
from ..functions.vectors import l2
from ..session import materialize, small
from .joins import cell_of, cuts_of, knn_join


def top(found: DataFrame, k: int | None = None) -> DataFrame:
    """qid, rank, oid, dist: the nearest k of each query; ties to smaller ids. Spark limits each group before the shuffle."""
    w = W.partitionBy("qid").orderBy("dist", "oid")
    limit = F.col("k") if k is None else F.lit(k)
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= limit).select("qid", "rank", "oid", "dist")


def _meets(terms, asked, held):
    ok = True
    for t in terms:
        left, right = held[t.end][None, :], asked[t.query][:, None]
        ok = ok & (left >= right if t.op == ">=" else left <= right)
    return ok


ENDS = ("s", "t", "sq", "tq")


def filtered_knn(objects: DataFrame, queries: DataFrame, relation: Relation | None, where: Column | None = None) -> DataFrame:
    """Ground truth: every valid object of every query, nearest k kept. relation None: all objects. where: a further filter on the objects' payload, pushed to the scan.

    The stated queries meet each batch of objects as one matrix product, masked by the relation; a batch hands on k of each query at most.
    """
    o, q = on_axis(objects if where is None else objects.where(where), "s", "t") if relation else (objects if where is None else objects.where(where)), queries
    most = q.agg(F.max("k")).first()[0]
    if most is None:
        return _nothing(o, q)
    if relation:
        q = on_axis(q, "sq", "tq")
    found = knn_join(q, o, most, (lambda asked, held: _meets(relation.terms, asked, held)) if relation else None, ENDS if relation else ())
    return top(found.join(q.select("qid", "k"), "qid"))


def _nothing(objects: DataFrame, queries: DataFrame) -> DataFrame:
    return top(objects.select("oid").join(queries.select("qid", "k"), F.lit(False)).select("qid", "k", "oid", F.lit(0.0).alias("dist")))


def interval_join(objects: DataFrame, queries: DataFrame, relation: Relation, method: str = "broadcast", cells: int = 64) -> DataFrame:
    """qid, oid of all valid pairs, without vectors.

    `broadcast`: queries are tested in each task, if there are few. `dominance`: objects are dealt into ranges of X, and a query goes to those
    that reach its x; Y is tested there. `bucketed`, for overlaps: both sides are cut at grid cells and joined on equal cells, and a pair is
    reported by the cell that holds the later of the two starts, so once.
    """
    if method == "broadcast":
        return objects.join(small(queries), relation.predicate()).select("qid", "oid")
    if method == "dominance":
        plan = relation.plan()
        o, q = attach(objects, plan), attach_queries(queries, plan)
        cuts = cuts_of(o, "x", cells)
        cell = lambda x: cell_of(x, cuts)
        sent = q.withColumn("cell", F.explode(F.sequence(cell(F.col("xq")), F.lit(len(cuts)))))  # up to cells rows a query
        return o.withColumn("cell", cell(F.col("x"))).join(sent, "cell").where((F.col("x") >= F.col("xq")) & (F.col("y") <= F.col("yq"))).select("qid", "oid")
    if relation.name != "overlaps":
        raise ValueError("grid cells serve overlaps")
    low, high = objects.agg(F.min("s"), F.max("t")).first()
    if low is None:
        return interval_join(objects, queries, relation)
    width = (high - low) / cells or 1.0
    cell = lambda x: F.least(F.greatest(F.floor((F.col(x) - low) / width), F.lit(0)), F.lit(cells)).cast("int")
    o = objects.withColumn("cell", F.explode(F.sequence(cell("s"), cell("t"))))
    q = queries.where("sq <= tq").withColumn("cell", F.explode(F.sequence(cell("sq"), cell("tq"))))
    home = F.greatest(cell("s"), cell("sq")) == F.col("cell")
    return o.join(q, "cell").where(relation.predicate() & home).select("qid", "oid")


def two_scalar(objects: DataFrame, queries: DataFrame, relation: Relation, depth: int | None = None) -> DataFrame:
    """Baseline: each comparison filtered on its own, nearest depth of each kept (all, if None), and the two lists intersected.

    Lists of a depth are merged over all batches before they meet. Whole lists are marks of a batch's objects, and what both mark is ranked there.
    """
    o, q = on_axis(objects, *ENDS[:2]), on_axis(queries, *ENDS[2:])
    most = q.agg(F.max("k")).first()[0]
    if most is None:
        return _nothing(o, q)
    marks = lambda term: lambda asked, held: _meets((term,), asked, held)
    a, b = (marks(t) for t in relation.terms)
    if depth is None:
        found = knn_join(q, o, most, lambda asked, held: a(asked, held) & b(asked, held), ENDS)
    else:
        found = top(knn_join(q, o, depth, a, ENDS), depth).select("qid", "oid", "dist").intersect(top(knn_join(q, o, depth, b, ENDS), depth).select("qid", "oid", "dist"))
    return top(found.join(q.select("qid", "k"), "qid"))


def prefilter(objects: DataFrame, queries: DataFrame, relation: Relation) -> DataFrame:
    """Baseline: valid objects first, by their coordinates; distances for those alone. Queries go in the order of x, some at a time, to the objects that reach one of them: no pair of a query and an object leaves its task."""
    plan = relation.plan()
    o, q = attach(objects, plan), attach_queries(queries, plan)
    most = q.agg(F.max("k")).first()[0]
    if most is None:
        return _nothing(o, q)
    near = lambda asked, held: np.flatnonzero((held["x"] >= asked["xq"].min()) & (held["y"] <= asked["yq"].max()))
    valid = lambda asked, held: (held["x"][None] >= asked["xq"][:, None]) & (held["y"][None] <= asked["yq"][:, None])
    q = q.where("xq is not null and yq is not null")
    found = knn_join(q, o, most, valid, ("x", "y", "xq", "yq"), near=near, by="xq")
    return top(found.join(q.select("qid", "k"), "qid"))


def by_predicate(objects: DataFrame, queries: DataFrame, predicate: Column, depths: tuple[int, ...] = (64, 512)) -> DataFrame:
    """The k nearest objects for which predicate, any expression over both sides, holds: exact.

    A query's nearest objects of all, in their order, are tested first; one with k valid among them is answered. Those that are not try a longer
    list, and what is left after the last, so queries with few valid objects, is tested against every object.
    """
    done, left = None, queries
    for depth in depths:
        # What comes after a list is farther, or as far with a larger oid.
        listed = top(knn_join(left, objects, depth), depth).select("qid", "oid", "dist")
        tested = listed.join(left, "qid").join(objects, "oid").where(predicate)
        valid = materialize(tested.select("qid", "k", "oid", "dist"), "valid")
        full = materialize(valid.groupBy("qid").agg(F.count(F.lit(1)).alias("n"), F.max("k").alias("k")).where("n >= k").select("qid"), "full")
        part = top(valid.join(full, "qid", "left_semi"))
        done = part if done is None else done.union(part)
        left = left.join(full, "qid", "left_anti")
    rest = top(objects.join(small(left), predicate).select("qid", "k", "oid", l2("vec", "qvec").alias("dist")))
    return rest if done is None else done.union(rest)
