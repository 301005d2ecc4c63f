"""The parts that no DataFrame expression can say: diversity pruning, threshold sweeps, repair edges, labelled walks.

Objects of a shard are numbered 0, 1, ... by (y, oid); xr and yr are their dense ranks. An edge (other, l, r, b) of an object is
alive in state (a, c) iff l <= a <= r and b <= c.
"""

from __future__ import annotations

import heapq

import numpy as np

PLAIN, PATCH = 0, 1


def dist2(v: np.ndarray, ids, q: np.ndarray) -> np.ndarray:
    e = v[ids] - q
    return np.einsum("ij,ij->i", e, e)


def pairs2(v: np.ndarray, ids: np.ndarray, q: np.ndarray, of: np.ndarray, block: int = 512) -> np.ndarray:
    """dist2() of the pairs (v[ids], q[of]), some at a time, so that they stay in the processor's cache."""
    out = np.empty(len(ids))
    a, b = np.empty((2, min(block, len(ids)), v.shape[1]))
    for at in range(0, len(ids), block):
        m = min(block, len(ids) - at)
        e = np.take(v, ids[at : at + m], 0, out=a[:m], mode="clip")  # clip: straight into out
        e -= np.take(q, of[at : at + m], 0, out=b[:m], mode="clip")
        np.einsum("ij,ij->i", e, e, out=out[at : at + m])
    return out


def diversify(v: np.ndarray, ids: np.ndarray, d: np.ndarray, m: int, kept: list | None = None) -> list[int]:
    """Of candidates in the order of (distance, id), those with no kept one that is strictly nearer both to the centre and to them; at most m."""
    kept, left, d = list(kept or []), np.asarray(ids, np.int64), np.asarray(d)
    for i in kept:
        far = dist2(v, left, v[i]) >= d
        left, d = left[far], d[far]
    while len(kept) < m and len(left):
        i, x = int(left[0]), d[0]
        kept.append(i)
        left, d = left[1:], d[1:]
        far = (x >= d) | (dist2(v, left, v[i]) >= d)
        left, d = left[far], d[far]
    return kept


def earlier(v: np.ndarray, oid: np.ndarray, j: int) -> tuple[np.ndarray, np.ndarray]:
    """Objects before j by (distance to j, oid), with squared distances."""
    d = dist2(v, np.arange(j), v[j])
    order = np.lexsort((oid[:j], d))
    return order, d[order]


def sweep_exact(v, oid, xr, j: int, m: int, width: int | None = None):
    """(edges (u, l, r), rounds) of object j: at each threshold the nearest earlier objects at or above it, pruned; then a leap past the least rank among them."""
    ids, d = earlier(v, oid, j)
    edges, x, rounds, w = [], 0, 0, width or m
    ranks = xr[ids]
    while x <= xr[j]:
        at = np.flatnonzero(ranks >= x)[:w]
        if not len(at):
            break
        right = min(int(xr[j]), int(ranks[at].min()))
        edges += [(u, x, right) for u in diversify(v, ids[at], d[at], m)]
        x, rounds = right + 1, rounds + 1
    return edges, rounds


def pools(v, oid, z: int, block: int = 256):
    """(j, ids, squared distances) of the z nearest earlier objects of each j, by (distance, oid): chosen by a matrix product of a block, with all that rounding could bring in, and measured anew."""
    n, sq = len(v), np.einsum("ij,ij->i", v, v)
    for at in range(1, n, block):
        to = min(n, at + block)
        rough = sq[:to][None] + sq[at:to, None] - 2 * (v[at:to] @ v[:to].T)
        for j in range(at, to):
            row = rough[j - at, :j]
            if j > z:
                edge = row[np.argpartition(row, z - 1)[:z]].max()
                ids = np.flatnonzero(row <= edge + 1e-9 * (sq[j] + abs(edge) + 1))
            else:
                ids = np.arange(j)
            d = dist2(v, ids, v[j])
            order = np.lexsort((oid[ids], d))[:z]
            yield j, ids[order], d[order]


def closer(v, ids, d) -> np.ndarray:
    """[w, u]: w is strictly nearer to the centre than u, and nearer to u than the centre is."""
    c = v[ids]
    sq = np.einsum("ij,ij->i", c, c)
    between = sq[:, None] + sq - 2 * (c @ c.T)
    return (between < d[None]) & (d[:, None] < d[None])


def keep(alive: np.ndarray, close: np.ndarray, m: int) -> list[int]:
    """diversify() on places: of the places alive, in their order, those that no kept one is closer to; at most m."""
    alive, kept = alive.copy(), []
    while len(kept) < m:
        i = int(alive.argmax())
        if not alive[i]:
            break
        kept.append(i)
        alive[i] = False
        alive &= ~close[i]
    return kept


def sweep_pooled(v, xr, j: int, ids, d, m: int, leap: str = "max", quantile: float = 0.75):
    """(edges, rounds, uncovered) of object j from one pool of earlier objects: uncovered is the range of thresholds left when the pool has none for them.

    Where a leap outlasts some of the kept, each of their places goes, from its end on, to the nearest unpruned object that lasts to the end of the leap.
    """
    edges, x, rounds, ranks, close = [], 0, 0, xr[ids], closer(v, ids, d)
    begun = {}  # who got a place in the last leap, and since when: one edge, if it is kept next
    while x <= xr[j]:
        at = ranks >= x
        if not at.any():
            return edges + [(u, l, x - 1) for u, l in begun.items()], rounds, (x, int(xr[j]))
        held = np.array(keep(at, close, m))
        kept = ids[held]
        own = np.sort(xr[kept])
        stop = {"full": ranks[at].min(), "conservative": own[0], "aggressive": own[int(quantile * (len(own) - 1))], "max": own[-1]}[leap]
        stop = min(int(stop), int(xr[j]))
        edges += [(int(u), begun.pop(int(u), x), min(stop, int(xr[u]))) for u in kept]
        edges += [(u, l, x - 1) for u, l in begun.items()]
        begun, gone = {}, own[own < stop]
        if len(gone):
            last = at & (ranks >= stop)
            last[held] = False
            fill = keep(last & ~close[held[ranks[held] >= stop]].any(0), close, len(gone))
            begun = {int(u): int(e) + 1 for u, e in zip(ids[fill], gone)}
        x, rounds = stop + 1, rounds + 1
    return edges + [(u, l, x - 1) for u, l in begun.items()], rounds, None


class Growing:
    """A graph under construction, for searches over it: each object's edges (other, l, r, b) as growing lists."""

    def __init__(self, n: int):
        self.lists = [[] for _ in range(n)]
        self.arrays: dict[int, tuple] = {}

    def add(self, src: int, edge: tuple) -> None:
        self.lists[src].append(edge)
        self.arrays.pop(src, None)

    def __getitem__(self, u: int) -> np.ndarray:
        if u not in self.arrays:
            self.arrays[u] = np.ascontiguousarray(np.array(self.lists[u], np.int64).reshape(-1, 4).T)
        return self.arrays[u]


def spread(graph: Growing, d: np.ndarray, a: int, start: int, size: int) -> np.ndarray:
    """Rows by distance d that a labelled search from start ends with, at most size, where all of graph is within the state's prefix: it expands what is new among its size nearest at once, until nothing is."""
    seen, done = np.zeros(len(d), bool), np.zeros(len(d), bool)
    seen[start], pool = True, np.array([start])
    while True:
        fresh = pool[~done[pool]]
        if not len(fresh):
            return pool[np.lexsort((pool, d[pool]))]
        done[fresh] = True
        other, l, r, _ = np.concatenate([graph[u] for u in fresh.tolist()], 1)
        near = other[(l <= a) & (a <= r)]
        near = np.unique(near[~seen[near]])
        seen[near] = True
        pool = np.concatenate([pool, near])
        if len(pool) > size:
            pool = pool[np.argpartition(d[pool], size - 1)[:size]]


def sweep_by_search(v, xr, j: int, m: int, graph: Growing, width: int, starts: np.ndarray):
    """(edges, rounds) of object j where each threshold's candidates come from a labelled search of the graph so far, in the state of the threshold and the object before j.

    Every state's graph is connected, as each object has an edge at every threshold with a valid earlier one: a pool that holds all valid objects gets them all, without a walk.
    A candidate that is not kept changes nothing when it ends, unless others may take its place in a full pool; so a round lasts as long as those kept, and one that stays keeps its edge.
    """
    d = dist2(v, np.arange(j), v[j])
    order, open_, edges, x, rounds = np.argsort(d, kind="stable"), {}, [], 0, 0
    ranks = xr[order]
    while x <= xr[j] and x <= xr[starts[j - 1]]:  # starts[i]: an object up to i with the largest x; beyond it none is valid
        ids = order[ranks >= x]
        full = len(ids) > width
        if full:
            ids = spread(graph, d, x, int(starts[j - 1]), width)
        kept = diversify(v, ids, d[ids], m)
        right = min(int(xr[j]), int(xr[ids if full and len(kept) < m else kept].min()))
        edges += [(u, l, x - 1) for u, l in open_.items() if u not in kept]
        open_ = {u: open_.get(u, x) for u in kept}
        x, rounds = right + 1, rounds + 1
    return edges + [(u, l, x - 1) for u, l in open_.items()], rounds


def mend(v, oid, xr, j: int, span: tuple[int, int], m: int, kp: int, how: str = "anchored"):
    """Repair edges (u, l, r) for the uncovered thresholds of object j.

    The pool holds earlier objects valid at its start, longest-lived first, up to m * kp. `anchored` takes two of the longest-lived whatever
    their distance, then prunes the rest by distance and fills up with the nearest; `lifetime` has no anchors; `previous` takes the latest m.
    """
    low, high = span
    pool = np.flatnonzero(xr[:j] >= low)
    if how == "none" or not len(pool):
        return []
    if how == "previous":
        chosen = pool[::-1][:m].tolist()
    else:
        life = np.minimum(xr[pool], high)
        pool = pool[np.lexsort((-pool, -xr[pool], -life))][: m * kp]
        anchors = pool[: min(2, m)].tolist() if how == "anchored" else []
        rest = pool[len(anchors) :]
        d = dist2(v, rest, v[j]) if len(rest) else np.zeros(0)
        order = np.lexsort((oid[rest], d))
        rest, d = rest[order], d[order]
        chosen = anchors + diversify(v, rest, d, m - len(anchors))
        chosen += [int(u) for u in rest if u not in set(chosen)][: m - len(chosen)]
    return [(int(u), low, min(int(xr[j]), int(xr[u]), high)) for u in chosen]


def walk(v, graph, q, a: int, c: int, start: int, size: int, labels: bool = True, admit=None, hop_through: bool = False, fan: int | None = None):
    """Best-first search from start along edges alive in (a, c): (ids, squared distances, costs), nearest first, at most size; costs are distance evaluations, expanded nodes and edges tested.

    graph[u] is (other, l, r, b) as arrays. Without labels every edge is followed; admit then tells which nodes may be results:
    others are passed over, or through where hop_through. fan: of a node's admitted neighbours only the first so many. Of equally near ones the smaller id counts as nearer.
    """
    d0 = float(dist2(v, [start], q)[0])
    seen, evals, hops, tests = {start}, 1, 0, 0
    ok = lambda x: admit is None or admit[x]
    best = [(-d0, -start)] if ok(start) else []
    todo = [(d0, start)]
    while todo:
        d, u = heapq.heappop(todo)
        if len(best) == size and (d, u) > (-best[0][0], -best[0][1]):
            break
        other, l, r, b = graph[u]
        hops, tests = hops + 1, tests + len(other)
        near = other[(l <= a) & (a <= r) & (b <= c)] if labels else other
        if admit is not None and not hop_through:
            near = near[admit[near]]
        near = [x for x in dict.fromkeys(near[:fan].tolist()) if x not in seen]
        if not near:
            continue
        seen.update(near)
        far = dist2(v, near, q)
        evals += len(near)
        for x, e in zip(near, far.tolist()):
            if len(best) < size or (e, x) < (-best[0][0], -best[0][1]):
                heapq.heappush(todo, (e, x))
                if ok(x):
                    heapq.heappush(best, (-e, -x))
                    if len(best) > size:
                        heapq.heappop(best)
    found = sorted((-d, -x) for d, x in best)
    return [x for _, x in found], [d for d, _ in found], (evals, hops, tests)


def walk_many(v, ends, dst, q, start, size: int, labels: tuple | None = None, a=None, c=None, admit=None, fan: int | None = None, span: tuple | None = None):
    """walk() for many queries side by side, each with its own start, state and mask [query, row] of admitted rows, none hopped through: (row of q, row, costs of each q), nearest first.

    In a round every query that has an unexpanded row in its pool expands the nearest one, as it would alone; only the order in which queries take turns differs.
    span (first, end): the rows that each query can get to, where graphs lie side by side.
    """
    first, rows = (np.zeros(len(q), np.int64), np.full(len(q), len(v))) if span is None else (span[0], span[1] - span[0])
    marks = np.cumsum(rows) - rows - first  # of a query's row: at marks + row
    if len(q) > 1 and rows.sum() > 1 << 24:
        half = len(q) // 2
        left, right = (walk_many(v, ends, dst, q[s], start[s], size, labels, *(z if z is None else z[s] for z in (a, c, admit)), fan, span and tuple(z[s] for z in span)) for s in (slice(half), slice(half, None)))
        return np.concatenate([left[0], right[0] + half]), *(np.concatenate(z) for z in zip(left[1:], right[1:]))
    n, costs, found = len(v), np.zeros((len(q), 3), np.int64), []
    own = np.arange(len(q))
    if labels is not None:
        x, y = (z.astype(labels[0].dtype) for z in (a, c))
    pool_d, pool_i, done = np.full((len(q), size), np.inf), np.full((len(q), size), n), np.ones((len(q), size), bool)  # sorted; n: no row
    pool_d[:, 0], pool_i[:, 0], done[:, 0] = pairs2(v, start, q, own), start, False
    met = np.full(rows.sum(), -1, np.int32)
    met[marks + start] = 0
    costs[:, 0] = 1
    while len(own):
        at = done.argmin(1)
        left = ~done[np.arange(len(own)), at]
        if not left.all():
            over = ~left
            row, col = np.nonzero(pool_i[over] < n)
            found.append((own[over][row], pool_i[over][row, col], col))
            own, at, pool_d, pool_i, done = own[left], at[left], pool_d[left], pool_i[left], done[left]
        here = np.arange(len(own))
        u = pool_i[here, at]
        done[here, at] = True
        long = ends[u + 1] - ends[u]
        costs[own, 1] += 1
        costs[own, 2] += long
        of = np.repeat(here, long)
        edge = np.arange(len(of)) + np.repeat(ends[u] - np.cumsum(long) + long, long)
        if labels is not None:
            l, r, b = labels
            ok = np.flatnonzero(r[edge] >= np.repeat(x[own], long))
            of, edge = of[ok], edge[ok]
            for low, state in ((l, x), (b, y)):
                ok = np.flatnonzero(low[edge] <= state[own][of])
                of, edge = of[ok], edge[ok]
        near = dst[edge].astype(np.int64)
        if admit is not None:
            ok = np.flatnonzero(admit.reshape(-1)[(own * n)[of] + near])
            of, near = of[ok], near[ok]
        if fan is not None:
            ok = np.flatnonzero(turns(of, len(own)) < fan)
            of, near = of[ok], near[ok]
        mark = marks[own][of] + near
        ok = np.flatnonzero(met[mark] < 0)
        of, near, mark = of[ok], near[ok], mark[ok]
        turn = np.arange(len(mark), dtype=np.int32)
        met[mark] = turn
        ok = np.flatnonzero(met[mark] == turn)  # one of those that an expansion lists twice
        if len(ok) < len(of):
            of, near = of[ok], near[ok]
        costs[own, 0] += np.bincount(of, minlength=len(own))
        d = pairs2(v, near, q, own[of])
        last = pool_d[:, -1][of]
        ok = np.flatnonzero((d < last) | (d == last) & (near < pool_i[:, -1][of]))
        if not len(ok):
            continue
        of, near, d = of[ok], near[ok], d[ok]
        place = turns(of, len(own))
        grown, to = np.unique(of, return_inverse=True)
        new_d, new_i = np.full((len(grown), place.max() + 1), np.inf), np.full((len(grown), place.max() + 1), n)
        new_d[to, place], new_i[to, place] = d, near
        both_d, both_i = np.concatenate([pool_d[grown], new_d], 1), np.concatenate([pool_i[grown], new_i], 1)
        order = both_d.argsort(1, kind="stable")
        d, i = np.take_along_axis(both_d, order, 1), np.take_along_axis(both_i, order, 1)
        tied = np.flatnonzero(((d[:, 1:] == d[:, :-1]) & (i[:, 1:] < i[:, :-1])).any(1))
        if len(tied):
            order[tied] = np.lexsort((both_i[tied], both_d[tied]))
            d[tied], i[tied] = np.take_along_axis(both_d[tied], order[tied], 1), np.take_along_axis(both_i[tied], order[tied], 1)
        ended = np.concatenate([done[grown], new_i == n], 1)
        pool_d[grown], pool_i[grown], done[grown] = d[:, :size], i[:, :size], np.take_along_axis(ended, order[:, :size], 1)
    of, ids, place = (np.concatenate(z) for z in zip(*found)) if found else (np.zeros(0, np.int64) for _ in range(3))
    order = np.lexsort((place, of))
    return of[order], ids[order], costs


def turns(of: np.ndarray, n: int) -> np.ndarray:
    """The place of each row among those with its number, from 0; of is in order, under n."""
    many = np.bincount(of, minlength=n)
    return np.arange(len(of)) - (np.cumsum(many) - many)[of]


def reach(n: int, ends, dst, start, labels: tuple | None = None, a=None, c=None) -> np.ndarray:
    """[query, row]: the rows that a walk gets to from each query's start where nothing ends it early, that is where its pool holds them all.

    Queries go side by side, 64 in a word, level by level. labels (l, r, b): edges alive in each query's state (a, c) alone; without, every edge.
    """
    words, at = -(-len(start) // 64), np.arange(len(start))
    word, bit = at // 64, np.uint64(1) << (at % 64).astype(np.uint64)
    seen = np.zeros((n, words), np.uint64)
    np.bitwise_or.at(seen, (start, word), bit)
    order = np.argsort(dst, kind="stable")
    src, to = np.repeat(np.arange(n), np.diff(ends))[order], dst[order]
    first = np.flatnonzero(np.concatenate([[True], to[1:] != to[:-1]])) if len(to) else np.zeros(0, np.int64)
    rows = to[first]
    alive = None
    if labels is not None and len(to):
        l, r, b = (z[order] for z in labels)

        def table(ranks, size, down):  # the queries whose rank is at most (or, going down, at least) each rank
            t = np.zeros((size, words), np.uint64)
            np.bitwise_or.at(t, (ranks, word), bit)
            return np.bitwise_or.accumulate(t[::-1], 0)[::-1] if down else np.bitwise_or.accumulate(t, 0)

        xs, ys = int(max(r.max(), l.max(), a.max())) + 1, int(max(b.max(), c.max())) + 1
        alive = table(a, xs, False)[r] & table(a, xs, True)[l] & table(c, ys, True)[b]
    while len(to):
        sent = seen[src] if alive is None else seen[src] & alive
        new = np.bitwise_or.reduceat(sent, first, 0) & ~seen[rows]
        if not new.any():
            break
        seen[rows] |= new
    return np.unpackbits(np.ascontiguousarray(seen.astype("<u8")).view(np.uint8), axis=1, bitorder="little")[:, : len(start)].T.astype(bool)


def prefix_tops(xr) -> np.ndarray:
    """For each place the first object up to it that has the largest x so far: an entry of every state that has a valid object there."""
    top = np.maximum.accumulate(xr)
    return np.maximum.accumulate(np.where(np.concatenate([[True], top[1:] > top[:-1]]), np.arange(len(xr)), 0))


def build(v, oid, xr, yr, m: int, method: str = "exact", pool: int = 100, leap: str = "max", patch: str = "anchored", kp: int = 8, pool_by: str = "scan"):
    """Directed edges (src, dst, l, r, b, kind) of a shard and (rounds, uncovered ranges).

    `exact` and `practical` with pools by `scan` link an object to earlier ones by their data alone. Pools by `graph` come from one broad
    search of the graph so far, without labels; `incremental` searches that graph at every threshold, with labels: both insert one object after the other.
    """
    rows, rounds, open_ = [], 0, 0
    growing = Growing(len(v)) if method == "incremental" or pool_by == "graph" else None
    scanned = pools(v, oid, pool) if method == "practical" and growing is None else None
    starts = prefix_tops(xr) if len(v) else None
    for j in range(1, len(v)):
        extra = []
        if method == "exact":
            edges, n = sweep_exact(v, oid, xr, j, m)
        elif method == "incremental":
            edges, n = sweep_by_search(v, xr, j, m, growing, max(pool, m), starts)
        else:
            if scanned is not None:
                _, ids, d = next(scanned)
            else:
                ids, d, _ = walk(v, growing, v[j], 0, 0, j - 1, pool, labels=False)
                ids, d = np.array(ids, np.int64), np.array(d)
            edges, n, gap = sweep_pooled(v, xr, j, ids, d, m, leap)
            extra = mend(v, oid, xr, j, gap, m, kp, patch) if gap else []
            open_ += gap is not None
        rounds += n
        for kind, some in ((PLAIN, edges), (PATCH, extra)):
            for u, l, r in some:
                rows += [(j, u, l, r, int(yr[j]), kind), (u, j, l, r, int(yr[j]), kind)]
                if growing is not None:
                    growing.add(j, (u, l, r, int(yr[j])))
                    growing.add(u, (j, l, r, int(yr[j])))
    return rows, rounds, open_


def dense(v, oid, width: int):
    """Edges of every object to its width nearest ones, nearest first, unpruned: the graph of a walk that tests the predicate itself."""
    n, sq = len(v), np.einsum("ij,ij->i", v, v)
    out = []
    for at in range(0, n, 256):
        rough = sq[None] + sq[at : at + 256, None] - 2 * (v[at : at + 256] @ v.T)
        for i, row in enumerate(rough):
            row[at + i] = np.inf
            ids = np.argpartition(row, min(width, n - 1) - 1)[:width] if n > 1 else np.zeros(0, np.int64)
            out.append(ids[np.lexsort((oid[ids], row[ids]))])
    return out


def levels(oid, ratio: int) -> np.ndarray:
    """A geometric draw for each oid: level l with a share of 1/ratio of those on l - 1."""
    h = (oid.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    u = ((h ^ (h >> np.uint64(32))) >> np.uint64(11)).astype(np.float64) / 2**53
    return np.floor(-np.log(np.maximum(u, 1e-18)) / np.log(ratio)).astype(np.int64)


def dedicated(v, oid, xr, yr, a: int, c: int, m: int) -> set[tuple[int, int]]:
    """Edges of the insertion-only graph on the objects valid in one state."""
    valid = np.flatnonzero((xr >= a) & (yr <= c))
    out = set()
    for i in range(1, len(valid)):
        j, before = valid[i], valid[:i]
        d = dist2(v, before, v[j])
        order = np.lexsort((oid[before], d))[:m]
        for u in diversify(v, before[order], d[order], m):
            out |= {(int(j), int(u)), (int(u), int(j))}
    return out
