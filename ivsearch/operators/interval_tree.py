"""Baselines that keep several plain graphs: a tree of them over the plane of (s, t), for containment, and levels of ever fewer objects."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ..functions.coords import attach, attach_queries, whole
from ..functions.relations import CONTAINED, Relation
from ..session import materialize
from . import blobs, kernels
from .index import PACKED, Shard, _arrays, assign, by_shard, each_shard, merged
from .joins import measured, nearest_in, nearest_of


def _plain(v, oid, m: int, pool: int) -> list[np.ndarray]:
    """Each row's neighbours in a graph that is swept once."""
    zero, out = np.zeros(len(oid), np.int64), [[] for _ in oid]
    for src, dst, *_ in kernels.build(v, oid, zero, zero, m, "practical", pool, "full", "none")[0]:
        out[src].append(dst)
    return [np.array(x, np.int64) for x in out]


def _flat(lists: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    return np.concatenate([[0], np.cumsum([len(x) for x in lists])]).astype(np.int64), np.concatenate([*lists, np.zeros(0, np.int64)])


def _packed(objects: DataFrame, relation: Relation, shard_rows: int, make) -> DataFrame:
    placed = assign(attach(whole(objects), relation.plan()), shard_rows).select("shard", "oid", "vec", "x", "y")

    def run(key, t):
        v, oid, x, y, *_ = _arrays(t)
        none = np.zeros(0, np.int32)
        blob = blobs.pack(oid=oid, v=v, x=x, y=y, ends=np.zeros(len(oid) + 1, np.int64), dst=none, l=none, r=none, b=none, **make(v, oid, x, y))
        return pa.Table.from_arrays([pa.array([key[0].as_py()], pa.int32()), pa.array([len(oid)], pa.int64()), pa.array([x.max()]), pa.array([y.min()]), pa.array([blob], pa.binary())], names=[c.split()[0] for c in PACKED.split(", ")])

    return materialize(by_shard(placed).applyInArrow(run, PACKED), "packed")


class Listed:
    """Neighbours by row, as a graph for walks without labels."""

    def __init__(self, ends, dst):
        self.ends, self.dst = ends, dst

    def __getitem__(self, u: int) -> tuple:
        near = self.dst[self.ends[u] : self.ends[u + 1]]
        return near, near, near, near


class Tree(Shard):
    def __init__(self, blob: bytes):
        super().__init__(blob)
        a = blobs.unpack(blob)
        self.rows, self.of, self.kids, self.box = a["rows"], a["of"], a["kids"], a["box"]
        self.node_ends, self.near_ends, self.near = a["node_ends"], a["near_ends"], a["near"]
        self.whole: dict[int, tuple] = {}
        self.joined: tuple | None = None

    def take(self, q, xq: float, yq: float, k: int, ef: int) -> tuple[np.ndarray, np.ndarray, tuple]:
        todo, hits, costs = [0] if len(self.of) else [], [], np.zeros(3, np.int64)
        while todo:
            i = todo.pop()
            rows = self.rows[self.of[i, 0] : self.of[i, 1]]
            low, high = self.box[i]
            if self.x[rows].max() < xq or self.y[rows].min() > yq:
                continue
            if low >= xq and high <= yq and self.of[i, 2] >= 0:
                at = self.of[i, 2]
                graph = Listed(self.near_ends[at : at + len(rows) + 1], self.near)
                found, _, spent = kernels.walk(self.v[rows], graph, q, 0, 0, 0, max(ef, k), labels=False)
                hits.append(rows[found])
                costs += spent
            elif self.kids[i, 0] >= 0 and not (low >= xq and high <= yq):
                todo += self.kids[i].tolist()
            else:
                hits.append(rows[(self.x[rows] >= xq) & (self.y[rows] <= yq)])
                costs[0] += len(hits[-1])
        ids = np.concatenate([*hits, np.zeros(0, np.int64)]).astype(np.int64)
        d = measured(q[None], self.v, np.zeros(len(ids), np.int64), ids)
        best = np.lexsort((self.oid[ids], d))[:k]
        return ids[best], d[best], tuple(int(c) for c in costs)

    def within(self, i: int, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(rows, costs) of a walk of a node's graph whose pool holds them all: the same for every query."""
        if i not in self.whole:
            at = self.of[i, 2]
            ends = self.near_ends[at : at + len(rows) + 1]
            seen = np.flatnonzero(kernels.reach(len(rows), ends - ends[0], self.near[ends[0] : ends[-1]], np.zeros(1, np.int64))[0])
            self.whole[i] = rows[seen], np.array([len(seen), len(seen), np.diff(ends)[seen].sum()])
        return self.whole[i]

    def graphs(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(vectors, neighbours, row of the shard) by place in near_ends: the graphs of all nodes as one."""
        if self.joined is None:
            held, dst = np.zeros(len(self.near_ends), np.int64), self.near.copy()
            for first, end, at in self.of[self.of[:, 2] >= 0].tolist():
                held[at : at + end - first] = self.rows[first:end]
                dst[self.near_ends[at] : self.near_ends[at + end - first]] += at
            self.joined = self.v[held], dst, held
        return self.joined

    def walk_many(self, q, xq, yq, k, ef: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """take() for a block of queries: all walks of a query and a node that it takes whole go side by side."""
        costs, pairs, whole = np.zeros((len(q), 3), np.int64), [], [(np.zeros(0, np.int64), 0, 0)]
        todo = [(0, np.arange(len(q)))] if len(self.of) else []
        while todo:
            i, of = todo.pop()
            rows = self.rows[self.of[i, 0] : self.of[i, 1]]
            low, high = self.box[i]
            x, y = self.x[rows], self.y[rows]
            of = of[(x.max() >= xq[of]) & (y.min() <= yq[of])]
            inside = (low >= xq[of]) & (high <= yq[of])
            if self.of[i, 2] >= 0:
                whole.append((of[inside], self.of[i, 2], self.of[i, 2] + len(rows)))
                of, inside = of[~inside], inside[~inside]
            if self.kids[i, 0] >= 0:
                todo += [(int(kid), of[~inside]) for kid in self.kids[i]] if (~inside).any() else []
                of = of[inside]
            ok = (x >= xq[of][:, None]) & (y <= yq[of][:, None])
            costs[of, 0] += ok.sum(1)
            at, col = np.nonzero(ok)
            pairs.append((of[at], rows[col]))
        taken, (first, end) = np.concatenate([w[0] for w in whole]), (np.repeat([w[z] for w in whole], [len(w[0]) for w in whole]) for z in (1, 2))
        v, dst, held = self.graphs()
        for width in np.unique(np.maximum(ef, k[taken])).tolist():
            own = np.maximum(ef, k[taken]) == width
            at, found, spent = kernels.walk_many(v, self.near_ends, dst, q[taken[own]], first[own], min(width, int((end - first).max())), span=(first[own], end[own]))
            np.add.at(costs, taken[own], spent)
            pairs.append((taken[own][at], held[found]))
        of, rows = (np.concatenate([np.zeros(0, np.int64), *p]) for p in (zip(*pairs) if pairs else ((), ())))
        return *nearest_of(q, self.v, self.oid, k, of, rows), costs

    def take_many(self, q, xq, yq, k) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """take() for a block of queries where the pool holds every node's objects."""
        costs, hit = np.zeros((len(q), 3), np.int64), np.zeros((len(q), len(self.oid)), bool)
        todo = [(0, np.arange(len(q)))] if len(self.of) else []
        while todo:
            i, of = todo.pop()
            rows = self.rows[self.of[i, 0] : self.of[i, 1]]
            low, high = self.box[i]
            of = of[(self.x[rows].max() >= xq[of]) & (self.y[rows].min() <= yq[of])]
            inside = (low >= xq[of]) & (high <= yq[of])
            if self.of[i, 2] >= 0 and inside.any():
                found, spent = self.within(i, rows)
                hit[np.ix_(of[inside], found)] = True
                costs[of[inside]] += spent
                of, inside = of[~inside], inside[~inside]
            if self.kids[i, 0] >= 0 and (~inside).any():
                todo += [(int(kid), of[~inside]) for kid in self.kids[i]]
                of = of[inside]
            if len(of):
                ok = (self.x[rows][None] >= xq[of][:, None]) & (self.y[rows][None] <= yq[of][:, None])
                hit[np.ix_(of, rows)] = ok
                costs[of, 0] += ok.sum(1)
        return *nearest_in(q, self.v, self.oid, k, hit), costs


def build(objects: DataFrame, leaf: int = 64, m: int = 16, pool: int = 100, shard_rows: int = 4000) -> DataFrame:
    """The tree of graphs, stored, one row a shard: its plane is halved at medians of s and t in turn down to leaf objects; every node above a leaf has a graph of its own."""
    def make(v, oid, x, y):
        order, of, kids, box, near = [], [], [], [], []
        size = 0

        def split(ids, depth):
            nonlocal size
            i, own = len(of), ids[np.argsort(oid[ids])]
            order.append(own)
            big = len(own) > leaf
            of.append([size, size + len(own), sum(len(g) + 1 for g in near) if big else -1])
            size += len(own)
            kids.append([-1, -1])
            box.append([x[own].min(), y[own].max()])
            if big:
                near.append(_plain(v[own], oid[own], m, pool))
                axis = (x, y)[depth % 2][own]
                low = axis < np.median(axis)
                if 0 < low.sum() < len(own):
                    kids[i] = [split(own[low], depth + 1), split(own[~low], depth + 1)]
            return i

        if len(oid):
            split(np.arange(len(oid)), 0)
        ends, at = [], 0
        for graph in near:  # one entry more than rows for each graph, so that graphs lie side by side
            e, _ = _flat(graph)
            ends.append(e + at)
            at += int(e[-1])
        flat = np.concatenate([*(x for g in near for x in g), np.zeros(0, np.int64)])
        return {"rows": np.concatenate([*order, np.zeros(0, np.int64)]).astype(np.int64), "of": np.array(of, np.int64).reshape(-1, 3), "kids": np.array(kids, np.int64).reshape(-1, 2), "box": np.array(box, np.float64).reshape(-1, 2), "near_ends": np.concatenate([*ends, np.zeros(0, np.int64)]).astype(np.int64), "near": flat.astype(np.int64), "node_ends": np.zeros(0, np.int64)}

    return _packed(objects, CONTAINED, shard_rows, make)


def search(tree: DataFrame, queries: DataFrame, ef: int = 64, stats: bool = False) -> DataFrame:
    """qid, rank, oid, dist: a query takes the largest nodes that lie inside its rectangle whole, by their graphs, and the leaves that cross its edge, whose objects are tested one by one."""
    asked = attach_queries(queries, CONTAINED.plan())
    return merged(each_shard(tree, asked, lambda s, q, xq, yq, k: s.take(q, xq, yq, k, ef), Tree, lambda s, q, xq, yq, k: s.take_many(q, xq, yq, k) if ef >= len(s.oid) else s.walk_many(q, xq, yq, k, ef), costs=stats), stats)


class Layered(Shard):
    def __init__(self, blob: bytes):
        super().__init__(blob)
        a = blobs.unpack(blob)
        self.levels = [(a[f"m{i}"], Listed(a[f"e{i}"], a[f"d{i}"])) for i in range(int(a["levels"][0]))]

    def take(self, q, xq: float, yq: float, k: int, ef: int) -> tuple[np.ndarray, np.ndarray, tuple]:
        costs, at = np.zeros(3, np.int64), 0
        for i in range(len(self.levels) - 1, -1, -1):
            members, graph = self.levels[i]
            start = int(np.searchsorted(members, at)) if i < len(self.levels) - 1 else 0
            found, _, spent = kernels.walk(self.v[members], graph, q, 0, 0, start, max(ef, k) if i == 0 else 1, labels=False)
            costs += spent
            at = int(members[found[0]])
        ids = np.array([x for x in members[found] if self.x[x] >= xq and self.y[x] <= yq], np.int64)
        d = measured(q[None], self.v, np.zeros(len(ids), np.int64), ids)
        best = np.lexsort((self.oid[ids], d))[:k]
        return ids[best], d[best], tuple(int(c) for c in costs)

    def descend(self, q) -> tuple[np.ndarray, np.ndarray]:
        """(row at which each query enters the lowest level, costs so far): a greedy walk of all queries on each level above it."""
        costs, at = np.zeros((len(q), 3), np.int64), None
        for members, graph in self.levels[:0:-1]:
            start = np.zeros(len(q), np.int64) if at is None else np.searchsorted(members, at)
            _, found, spent = kernels.walk_many(self.v[members], graph.ends, graph.dst, q, start, 1)
            costs, at = costs + spent, members[found]
        return np.zeros(len(q), np.int64) if at is None else at, costs

    def walk_many(self, q, xq, yq, k, ef: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """take() for a block of queries, side by side on every level."""
        at, costs = self.descend(q)
        (members, graph), pairs = self.levels[0], []
        for width in np.unique(np.maximum(ef, k)).tolist():
            own = np.flatnonzero(np.maximum(ef, k) == width)
            of, found, spent = kernels.walk_many(self.v[members], graph.ends, graph.dst, q[own], np.searchsorted(members, at[own]), min(width, len(members)))
            costs[own] += spent
            of, rows = own[of], members[found]
            ok = (self.x[rows] >= xq[of]) & (self.y[rows] <= yq[of])
            pairs.append((of[ok], rows[ok]))
        of, rows = (np.concatenate([np.zeros(0, np.int64), *p]) for p in (zip(*pairs) if pairs else ((), ())))
        return *nearest_of(q, self.v, self.oid, k, of, rows), costs

    def take_many(self, q, xq, yq, k) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """take() for a block of queries where the pool holds the whole lowest level: all walk that level at once."""
        at, costs = self.descend(q)
        members, graph = self.levels[0]
        seen = kernels.reach(len(members), graph.ends, graph.dst, np.searchsorted(members, at))
        costs += np.stack([seen.sum(1), seen.sum(1), seen @ np.diff(graph.ends)], 1)
        hit = np.zeros((len(q), len(self.oid)), bool)
        hit[:, members] = seen
        hit &= (self.x[None] >= xq[:, None]) & (self.y[None] <= yq[:, None])
        return *nearest_in(q, self.v, self.oid, k, hit), costs


def build_layered(objects: DataFrame, relation: Relation, m: int = 16, pool: int = 200, shard_rows: int = 4000) -> DataFrame:
    """A layered small-world graph, stored, one row a shard: each level holds a geometric draw of the one below, about 1 in m, with a graph of its own."""
    def make(v, oid, x, y):
        drawn, out, level = kernels.levels(oid, m), {}, 0
        while level == 0 or (drawn >= level).any():
            members = np.flatnonzero(drawn >= level)
            out[f"m{level}"] = members.astype(np.int64)
            out[f"e{level}"], out[f"d{level}"] = _flat(_plain(v[members], oid[members], m, pool))
            level += 1
        return out | {"levels": np.array([level], np.int64)}

    return _packed(objects, relation, shard_rows, make)


def search_layered(graph: DataFrame, queries: DataFrame, relation: Relation, ef: int = 64, stats: bool = False) -> DataFrame:
    """Post-filter: a greedy descent through the upper levels, a walk of width ef on the lowest, and of what it finds the valid ones."""
    asked = attach_queries(queries, relation.plan())
    return merged(each_shard(graph, asked, lambda s, q, xq, yq, k: s.take(q, xq, yq, k, ef), Layered, lambda s, q, xq, yq, k: s.take_many(q, xq, yq, k) if ef >= len(s.oid) else s.walk_many(q, xq, yq, k, ef), costs=stats), stats)
