"""Runners of the experiments: methods, variants and parameters over workloads of stated selectivity, as rows of one measures table."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.relations import ALL, Relation
from ..operators import exact, index, interval_tree, measure
from ..session import materialize
from .workload import exact_count, objects

MEASURES = "dataset string, relation string, sigma double, method string, params map<string,string>, queries long, valid long, recall double, invalid long, evals double, hops double, tests double, qps double, build_s double, edges long, bytes long, objects long"
METHODS = ("walk", "post", "layered", "dense", "tree", "scan")


def timed(make):
    began = time.perf_counter()
    out = make()
    return out, time.perf_counter() - began


class Built:
    """An index of one method over objects, stored, and its cost."""

    def __init__(self, objs: DataFrame, relation: Relation, method: str, m: int = 8, pool: int = 100, gamma: int = 12, shard_rows: int = 4000, **how):
        self.relation, self.method, self.objects = relation, method, objs
        self.edges = self.bytes = 0
        rows = None
        if method in ("walk", "post", "dense"):
            def make():
                if method == "walk":
                    return materialize(index.build(objs, relation, m, how.pop("construct", "practical"), pool, shard_rows=shard_rows, **how), "index")
                return index.unlabelled(objs, relation, m, pool, shard_rows, gamma if method == "dense" else 0)

            rows, self.seconds = timed(make)
            self.stored = materialize(index.pack(rows), "packed")
            size = measure.index_size(rows).first()
            labelled = 16 if method == "walk" else 4  # other, l, r, b; other alone
            self.edges, self.bytes = size.edges or 0, (size.edges or 0) * labelled
        elif method == "layered":
            self.stored, self.seconds = timed(lambda: interval_tree.build_layered(objs, relation, m, pool, shard_rows))
        elif method == "tree":
            self.stored, self.seconds = timed(lambda: interval_tree.build(objs, 64, m, pool, shard_rows))
        else:
            self.stored, self.seconds = None, 0.0
        self.rows = rows
        if method in ("layered", "tree"):
            self.bytes = self.stored.agg(F.sum(F.octet_length("blob"))).first()[0] or 0

    def search(self, queries: DataFrame, ef: int = 128, m: int = 8) -> DataFrame:
        """qid, rank, oid, dist and, for graphs, evals, hops and tests."""
        if self.method == "scan":
            return exact.filtered_knn(self.objects, queries, self.relation)
        if self.method == "tree":
            return interval_tree.search(self.stored, queries, ef, stats=True)
        if self.method == "layered":
            return interval_tree.search_layered(self.stored, queries, self.relation, ef, stats=True)
        return index.search(self.stored, queries, self.relation, ef, mode=self.method, stats=True, fan=m)


def point(built: Built, queries: DataFrame, truth: DataFrame, dataset: str, sigma: float, params: dict, ef: int = 128, clock: bool = False) -> tuple:
    """One row of MEASURES: recall over the queries with valid objects, mean costs a query, and the returned rows that are not valid."""
    asked = queries.count()
    found, took = timed(lambda: materialize(built.search(queries, ef), "found"))
    if clock:  # the first run also starts workers and compiles
        found, took = timed(lambda: materialize(built.search(queries, ef), "found"))
    recall = measure.recall(found, truth).agg(F.avg("recall")).first()[0]
    paid = [c for c in ("evals", "hops", "tests") if c in found.columns]
    mean = found.groupBy("qid").agg(*[F.max(c).alias(c) for c in paid]).agg(*[F.avg(c).alias(c) for c in paid]).first().asDict() if paid else {}
    costs = [mean.get(c) for c in ("evals", "hops", "tests")]
    o, q = exact.on_axis(built.objects, "s", "t").select("oid", "s", "t"), exact.on_axis(queries, "sq", "tq").select("qid", "sq", "tq")
    wrong = found.join(o, "oid").join(q, "qid").where(~built.relation.predicate()).count()
    valid = queries.agg(F.sum("realised")).first()[0] if "realised" in queries.columns else None
    return (dataset, built.relation.name, sigma, built.method, {k: str(v) for k, v in params.items()}, asked, valid, recall, wrong, *costs, asked / took, built.seconds, built.edges, built.bytes, built.objects.count())


def table(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, MEASURES)


def prepared(spark, sf_dir, view, name, sigma, kind="uniform", limit=None):
    o, q = objects(spark, sf_dir, view, kind=kind)
    o = materialize(o if limit is None else o.where(F.col("oid") < limit), "objects")
    made, _ = exact_count(o, q.select("qid", "qvec"), ALL[name], sigma)
    return o, made, materialize(exact.filtered_knn(o, made, ALL[name]), "truth")


def methods(spark, sf_dir, view="syn", name="contained", sigmas=(0.001, 0.01, 0.05, 0.1, 0.5), which=METHODS, ef=128, clock=False, **how) -> DataFrame:
    """The main experiment: every method, built once, at every selectivity."""
    o, q = objects(spark, sf_dir, view)
    o, rows = materialize(o, "objects"), []
    built = {m: Built(o, ALL[name], m, **how) for m in which if m != "tree" or name == "contained"}
    for sigma in sigmas:
        made, _ = exact_count(o, q.select("qid", "qvec"), ALL[name], sigma)
        truth = materialize(exact.filtered_knn(o, made, ALL[name]), "truth")
        rows += [point(b, made, truth, view, sigma, {"ef": ef}, ef, clock) for b in built.values()]
    return table(spark, rows)


def variants(spark, sf_dir, parameter: str, values, view="syn", name="contained", sigma=0.01, ef=128, clock=False, **how) -> DataFrame:
    """One parameter of the index (patch, leap, kp, pool_by, construct, m, pool) over values, all else equal."""
    o, made, truth = prepared(spark, sf_dir, view, name, sigma)
    return table(spark, [point(Built(o, ALL[name], "walk", **how | {parameter: v}), made, truth, view, sigma, {parameter: v, "ef": ef}, ef, clock) for v in values])


def widths(spark, sf_dir, values=(10, 16, 32, 64, 128, 256, 512), view="syn", name="contained", sigma=0.05, which=("walk",), clock=False, **how) -> DataFrame:
    """The search's width over values: the points of a frontier."""
    o, made, truth = prepared(spark, sf_dir, view, name, sigma)
    return table(spark, [point(b, made, truth, view, sigma, {"ef": v}, v, clock) for b in (Built(o, ALL[name], m, **how) for m in which) for v in values])


def distributions(spark, sf_dir, kinds=("uniform", "normal", "skewed", "clustered", "hollow"), name="contained", sigmas=(0.01, 0.1), ef=128, clock=False, **how) -> DataFrame:
    """Generated intervals of each kind; params hold the kind."""
    rows = []
    for kind in kinds:
        o, q = objects(spark, sf_dir, "syn", kind=kind)
        o = materialize(o, "objects")
        b = Built(o, ALL[name], "walk", **how)
        for sigma in sigmas:
            made, _ = exact_count(o, q.select("qid", "qvec"), ALL[name], sigma)
            rows.append(point(b, made, materialize(exact.filtered_knn(o, made, ALL[name]), "truth"), "syn", sigma, {"distribution": kind, "ef": ef}, ef, clock))
    return table(spark, rows)


def prefixes(spark, sf_dir, sizes, view="syn", name="contained", sigma=0.05, ef=128, clock=False, **how) -> DataFrame:
    """The same experiment on the objects with the smallest oids: how size, time, costs and recall grow."""
    rows = []
    for n in sizes:
        o, made, truth = prepared(spark, sf_dir, view, name, sigma, limit=n)
        rows.append(point(Built(o, ALL[name], "walk", **how), made, truth, view, sigma, {"prefix": n, "ef": ef}, ef, clock))
    return table(spark, rows)


def build_table(spark, sf_dir, views=("syn", "price"), name="contained", which=("post", "dense", "tree", "walk"), **how) -> DataFrame:
    """dataset, method, objects, edges, bytes, build_s of every method on every view."""
    rows = []
    for view in views:
        o = materialize(objects(spark, sf_dir, view)[0], "objects")
        n = o.count()
        for m in which:
            b = Built(o, ALL[name], m, **how)
            rows.append((view, m, n, b.edges, b.bytes, b.seconds))
    return spark.createDataFrame(rows, "dataset string, method string, objects long, edges long, bytes long, build_s double")
