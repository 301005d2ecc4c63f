"""N-gram Jaccard join: exact classes of documents linked by similar shingle sets, by set-relation skipping."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import hidden, shown, small, stage, table, unstage, width

#: Bits of the frequency sketch, bytes handled at a time, buckets in which a set counts its shingles.
SKETCH_BITS, BATCH, BUCKETS = 18, 1_000_000, 64
#: 64-bit words of a set's parity bits: bit i tells whether an odd number of its shingles fall in cell i.
PARITY = 4
#: Lists with so many sets get further rounds of links, so many at most, on parts of about so many sets.
CROWD, ROUNDS, PART = 64, 4, 512
#: So many edges are joined into components by one task, of about 100 MB; more by rounds of shuffles.
FEW = 1_000_000
_M = (1 << 64) - 1
_B = 0x9E3779B97F4A7C15 | 1
_BLANK = np.zeros(256, bool)
_BLANK[[0x20, *range(0x09, 0x0E)]] = True
_BYTE = np.random.default_rng(20240229).integers(1, 2**63, 256, dtype=np.uint64) | np.uint64(1)
_POWERS: list[np.ndarray] = []


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _POWERS or len(_POWERS[0]) < n:
        n, (up, down) = max(n, 1 << 16), (np.full(max(n, 1 << 16), b, np.uint64) for b in (_B, pow(_B, -1, 1 << 64)))
        up[0] = down[0] = 1
        _POWERS[:] = [np.cumprod(up, dtype=np.uint64), np.cumprod(down, dtype=np.uint64)]
    return _POWERS[0], _POWERS[1]


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingle_hashes(texts: list[str | None], n: int = 3) -> list[np.ndarray]:
    """For each text the sorted distinct 64-bit hashes of its n-word shingles; A-Z are lower-cased, a shorter sequence of words is one shingle.

    All texts are hashed at once: a running polynomial over their bytes gives each word's hash as a difference.
    """
    data = [(t or "").encode("utf-8", "surrogatepass").lower() for t in texts]
    bounds = np.cumsum([0] + [len(d) + 1 for d in data])
    raw = np.frombuffer(b"\n".join(data) + b"\n", np.uint8)
    up, down = _powers(len(raw) + 1)
    inside = ~_BLANK[raw]
    edge = np.diff(np.concatenate([[False], inside, [False]]).astype(np.int8))
    start, end = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    run = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_BYTE[raw] * up[: len(raw)], dtype=np.uint64)])
    word = _mix((run[end] - run[start]) * down[start])
    first = np.searchsorted(start, bounds)
    roll = np.zeros(max(0, len(word) - n + 1), np.uint64)
    for i in range(n):
        roll = roll * np.uint64(0xD6E8FEB86659FD93) + word[i : i + len(roll)]
    roll = _mix(roll)
    out = []
    for a, b in zip(first, first[1:]):
        if b - a >= n:
            out.append(np.unique(roll[a : b - n + 1]))
        elif b > a:
            few = np.uint64(b - a)
            for w in word[a:b]:
                few = np.uint64((int(few) * 0xD6E8FEB86659FD93 + int(w)) & _M)
            out.append(_mix(np.array([few], np.uint64)))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def _pieces(batches: Iterator[pa.RecordBatch], *columns: str) -> Iterator[list[list]]:
    """Rows of the batches in pieces of about BATCH bytes of the last column; only a piece at a time becomes Python objects."""
    for batch in batches:
        cols = [batch.column(c) for c in columns]
        part = np.cumsum(pc.fill_null(pc.binary_length(cols[-1]), 0).to_numpy(zero_copy_only=False)) // BATCH
        cuts = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), len(part)]
        for i, j in zip(cuts, cuts[1:]):
            if j > i:
                yield [c.slice(i, j - i).to_pylist() for c in cols]


def frequency_classes(docs: DataFrame, n: int = 3) -> bytes:
    """A byte for each of 2^18 hash buckets of shingles: 0 where the number of documents is usual, else growing with it.

    Used only to order shingles, rare before frequent, so shared passages stay out of the prefixes; any order is right.
    Each task counts all its documents; counts are added in two levels of bounded groups. The sketch has a fixed size.
    """
    def count(batches):
        total = np.zeros(1 << SKETCH_BITS, np.int64)
        for (texts,) in _pieces(batches, "text"):
            sets = shingle_hashes(texts, n)
            if sets:
                total += np.bincount((np.concatenate(sets) >> np.uint64(64 - SKETCH_BITS)).astype(np.int64), minlength=len(total))
        chunks = total.reshape(64, -1)
        yield pa.RecordBatch.from_pydict({"chunk": pa.array(range(64), pa.int32()), "counts": pa.array([c.tobytes() for c in chunks], pa.binary())})

    def add(key, t):
        total = sum(np.frombuffer(c.as_py(), np.int64) for c in t.column("counts"))
        return pa.table({"chunk": pa.array([key[0].as_py()], pa.int32()), "counts": pa.array([total.tobytes()], pa.binary())})

    kind = "chunk int, counts binary"
    parts = docs.select("text").mapInArrow(count, kind).withColumn("part", F.floor(F.spark_partition_id() / 256))
    sums = parts.groupBy("chunk", "part").applyInArrow(add, kind).groupBy("chunk").applyInArrow(add, kind).collect()  # 64 rows
    total = np.concatenate([np.frombuffer(r.counts, np.int64) for r in sorted(sums, key=lambda r: r.chunk)]) if sums else np.zeros(1 << SKETCH_BITS)
    mean = total.mean()
    return np.clip(np.log2(np.maximum((total - mean) / (4 * np.sqrt(mean) + 1), 0.5)) + 1, 0, 255).astype(np.uint8).tobytes()


def set_prefixes(docs: DataFrame, classes: bytes, num: int, den: int, n: int = 3) -> DataFrame:
    """doc_id, n (set size), lo, hi (digest of the set), prefix: its first shingles, one of which any set of similarity num/den or more shares, hist: how many of the set fall in each bucket, parity: see PARITY."""
    def run(batches):
        rank = np.frombuffer(classes, np.uint8)
        for ids, texts in _pieces(batches, "doc_id", "text"):
            size, digest, prefix, hist, odd = [], [], [], [], []
            for s in shingle_hashes(texts, n):
                k = rank[(s >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)]
                ordered = s[np.argsort(k, kind="stable")] if k.any() else s
                size.append(len(s))
                cell = ((s >> np.uint64(24)) & np.uint64(64 * PARITY - 1)).astype(np.int64)
                odd.append(np.packbits((np.bincount(cell, minlength=64 * PARITY) & 1).astype(bool)).view("<i8"))
                hist.append(np.bincount((s & np.uint64(BUCKETS - 1)).astype(np.int64), minlength=BUCKETS).astype("<u4").tobytes())
                digest.append(np.frombuffer(hashlib.blake2b(s.tobytes(), digest_size=16).digest(), np.int64))
                prefix.append(ordered[: len(s) - -(-num * len(s) // den) + 1].astype(np.int64) if len(s) else s.astype(np.int64))
            d = np.array(digest).reshape(-1, 2)
            yield pa.RecordBatch.from_pydict({"doc_id": pa.array(ids, pa.int64()), "n": pa.array(size, pa.int32()), "lo": pa.array(d[:, 0]), "hi": pa.array(d[:, 1]), "prefix": pa.array(prefix, pa.list_(pa.int64())), "hist": pa.array(hist, pa.binary()), "parity": pa.array(odd, pa.list_(pa.int64()))})

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, n int, lo long, hi long, prefix array<long>, hist binary, parity array<long>")


def surely_apart(x0: list[Column], x1: list[Column], y0: list[Column], y1: list[Column]) -> Column:
    """Shingles by which any set of one group differs from any of another, at least: cells whose parity is one in all of the one and zero in all of the other.

    x0 and x1 are the bitwise and, and or, of the parity words of a group's sets; a single set is a group with both alike.
    """
    return sum((F.bit_count(a0.bitwiseAND(F.bitwise_not(b1)).bitwiseOR(b0.bitwiseAND(F.bitwise_not(a1)))) for a0, a1, b0, b1 in zip(x0, x1, y0, y1)), F.lit(0))


def words(column: str) -> list[Column]:
    return [F.col(column)[i] for i in range(PARITY)]


def lit(df: DataFrame, rows: int, few: int = 200_000) -> DataFrame:
    """df, which has so many rows at most, marked for broadcast if they are few: 200,000 of two or three numbers, 20,000 of wider rows."""
    return F.broadcast(df) if rows <= few else df


def fit(df: DataFrame, rows: int) -> DataFrame:
    """df in no more tasks than so many rows need: a table of a few thousand rows is not worth a task for each shuffle partition."""
    return df.coalesce(n) if (n := max(12, rows // 200)) < width(df.sparkSession) else df


def at_most(pairs: DataFrame, hists: DataFrame) -> DataFrame:
    """pairs (a, b), a staged table, with na, nb and most, which the intersection cannot exceed: in each bucket the sets share at most the smaller count, and cells of unlike parity hold a shingle that only one has."""
    def run(batches):
        for t in batches:
            x, y = (np.frombuffer(b"".join(t.column(c).to_pylist()), "<u4").reshape(-1, BUCKETS) for c in ("ha", "hb"))
            na, nb, apart = (t.column(c).to_numpy().astype(np.int64) for c in ("na", "nb", "apart"))
            most = pa.array(np.minimum(np.minimum(x, y).sum(1).astype(np.int64), (na + nb - apart) // 2))
            yield pa.RecordBatch.from_arrays([*(t.column(c) for c in ("a", "b", "na", "nb")), most], names=["a", "b", "na", "nb", "most"])

    own = lambda c: hists.select(F.col("rep").alias(c), F.col("n").alias("n" + c), F.col("hist").alias("h" + c), F.col("parity").alias("p" + c))
    apart = surely_apart(words("pa"), words("pa"), words("pb"), words("pb")).cast("int").alias("apart")
    n = pairs.count()
    if n <= 500_000:  # only these are joined
        hists = hists.join(F.broadcast(pairs.select(F.col("a").alias("id")).union(pairs.select("b"))), F.col("rep") == F.col("id"), "left_semi")
    return lit(lit(pairs.select("a", "b"), n).join(own("a"), "a"), n, 20_000).join(own("b"), "b").select("a", "b", "na", "nb", "ha", "hb", apart).mapInArrow(run, "a long, b long, na int, nb int, most long")


def overlaps(docs: DataFrame, pairs: DataFrame, n: int = 3) -> DataFrame:
    """pairs (a, b), a staged table, with na, nb and both: the sizes of the two sets and of their intersection, from the whole texts.

    Rows arrive sorted by a, so a set that many pairs share is hashed once for all that follow one another.
    """
    def run(batches):
        last: tuple = (None, None)
        for a, b, ta, tb in _pieces(batches, "a", "b", "ta", "tb"):
            fresh = [i for i in range(len(a)) if a[i] != (a[i - 1] if i else last[0])]
            sets, new = shingle_hashes(tb, n), iter(shingle_hashes([ta[i] for i in fresh], n))
            fresh, na, both = set(fresh), [], []
            for i, x in enumerate(a):
                if i in fresh:
                    last = (x, next(new))
                na.append(len(last[1]))
                both.append(len(np.intersect1d(last[1], sets[i], assume_unique=True)))
            yield pa.RecordBatch.from_pydict({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64()), "na": pa.array(na, pa.int32()), "nb": pa.array(map(len, sets), pa.int32()), "both": pa.array(both, pa.int32())})

    rows = pairs.count()
    ids = pairs.select(F.col("a").alias("id")).union(pairs.select("b"))
    ids = F.broadcast(ids) if rows <= 500_000 else small(stage(ids.distinct(), "ids"), 1_000_000)
    text = docs.join(ids, F.col("doc_id") == F.col("id"), "left_semi").select(F.col("doc_id").alias("i"), F.col("text").alias("t"))
    texts = lit(pairs.select("a", "b"), rows).join(text.withColumnsRenamed({"i": "b", "t": "tb"}), "b").join(text.withColumnsRenamed({"i": "a", "t": "ta"}), "a")
    return fit(texts.select("a", "b", "ta", "tb"), rows).mapInArrow(run, "a long, b long, na int, nb int, both int")


def joined(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes of the edges (a, b), and of each the smallest node reachable."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    root = np.arange(len(nodes))
    while len(x):
        low = np.minimum(root[x], root[y])
        for z in (x, y):
            np.minimum.at(root, root[z], low)
        while (root[root] != root).any():
            root = root[root]
        left = root[x] != root[y]
        x, y = x[left], y[left]
    return nodes, nodes[root]


def components(edges: DataFrame) -> DataFrame:
    """node, component (the smallest node reachable) of undirected edges (a, b), which are counted first, for nodes with edges.

    Up to FEW edges are joined by one task. Beyond that, alternating stars: every node hooks its larger neighbours, then its smaller
    ones, to the smallest it knows. Each round is a few shuffles, written to the shared folder; rounds grow with the logarithm of the
    nodes. Nothing is gathered there.
    """
    def run(batches):
        some = [np.stack([t.column(c).to_numpy() for c in ("a", "b")]) for t in batches]
        for node, component in [joined(*np.concatenate(some, 1))] if some else []:
            yield pa.RecordBatch.from_arrays([pa.array(node), pa.array(component)], ["node", "component"])

    if edges.count() <= FEW:
        return edges.select("a", "b").coalesce(1).mapInArrow(run, "node long, component long")

    def state(df):
        return tuple(df.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())

    now = stage(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    seen = state(now)
    while True:
        two = now.union(now.select("b", "a"))
        least = two.groupBy(F.col("a").alias("u")).agg(F.least(F.col("a"), F.min("b")).alias("m"))
        large = two.join(least, F.col("a") == F.col("u")).where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        low = large.groupBy(F.col("a").alias("u")).agg(F.min("b").alias("m"))
        hooked = large.join(low, F.col("a") == F.col("u")).select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").union(low).distinct()
        then = stage(hooked.toDF("a", "b"), "edges")
        new = state(then)
        unstage(now)
        now, seen, done = then, new, new == seen
        if done:
            return now.select(F.col("a").alias("node"), F.col("b").alias("component")).union(now.select("b", "b").distinct())


def nearest_apart(crowded: DataFrame, comp: DataFrame, num: int, den: int, seed: int) -> DataFrame:
    """Pairs (a, b) of lists: each set with the one of another component, and the one of the largest component, whose parity word is most like its own.

    Lists are dealt to parts by a hash of the set and the seed. Sets of a part are compared there, not written; which pairs come out only decides how soon components grow together.
    """
    def run(key, t):
        rep, n, left, pivot = (t.column(c).to_numpy().astype(np.int64) for c in ("rep", "n", "left", "pivot"))
        odd = t.column("odd").to_numpy().view(np.uint64)
        main = np.unique(pivot, return_counts=True)
        main = pivot == main[0][np.argmax(main[1])]
        found = []
        for i in range(0, len(rep), PART):  # a block of rows at a time against the part
            x = slice(i, i + PART)
            both, apart = n[x, None] + n, np.bitwise_count(odd[x, None] ^ odd).astype(np.int64)
            fit = (pivot[x, None] != pivot) & (n[x, None] * den >= n * num) & (n * den >= n[x, None] * num) & (np.minimum(left[x, None], left) * (num + den) >= num * both) & (apart * (num + den) <= (den - num) * both)
            for ok in (fit, fit & main):
                best = np.where(ok, apart, 1 << 20)
                at = best.argmin(1)
                some = ok[np.arange(len(at)), at]
                found.append((rep[x][some], rep[at[some]]))
        a, b = (np.concatenate(c) for c in zip(*found))
        return pa.table({"a": pa.array(np.minimum(a, b)), "b": pa.array(np.maximum(a, b))})

    part = F.pmod(F.xxhash64("rep", F.lit(seed)), F.ceil(F.col("of") / PART)).alias("part")
    rows = crowded.count()
    own = crowded.join(small(comp, 200_000), F.col("rep") == F.col("node"), "left").select("token", part, "rep", "n", "left", "odd", F.coalesce("component", "rep").alias("pivot"))
    return fit(fit(own.groupBy("token", "part").applyInArrow(run, "a long, b long"), rows).distinct(), rows)


def one_text_an_id(docs: DataFrame) -> DataFrame:
    """docs (doc_id, text) with one row an id, the one whose text sorts first. Texts are shuffled only for ids that repeat."""
    again = stage(docs.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("doc_id"), "again")
    if again.isEmpty():
        return docs
    again = small(again)
    first = docs.join(again, "doc_id", "left_semi").groupBy("doc_id").agg(F.min("text").alias("text"))
    return docs.join(again, "doc_id", "left_anti").union(stage(first, "firsttexts"))


def jaccard_classes(docs: DataFrame, num: int = 8, den: int = 10, n: int = 5) -> DataFrame:
    """doc_id, n_shingles, component_id: documents linked when intersection / union of their shingle sets is num/den or more.

    Equal sets are one set. What remains is an exact prefix join in two steps. First, neighbours in the size order of each
    index list, and each list's first, are verified, and the links joined into components; so a group of n near copies costs
    about n pairs, not n * n. Then lists are read block by block of sizes and positions, skipping blocks that the bounds exclude and
    sets of one component, which gives pairs of components that may still touch; the join that makes them also compares parity bits of their
    sets, a lower bound on how far they differ. The overlap of their two pivots is computed where counts by bucket allow a link; what a member
    can have in common with a set exceeds what its pivot has by at most the shingles it has beyond the pivot; only member pairs
    which that bound allows are verified. No link between different texts is lost.

    One row per distinct id (rows of one id are one document, with the text that sorts first; rows with null id are dropped).
    Null or wordless texts have an empty set and no links. Extra columns are ignored.
    """
    docs = one_text_an_id(docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")))
    classes = frequency_classes(docs, n)
    sets = stage(set_prefixes(docs, classes, num, den, n), "sets")
    reps = stage(sets.where("n > 0").groupBy("lo", "hi").agg(F.min("doc_id").alias("rep")), "reps")

    # Lists with more than one set, once for both steps.
    fold = reduce(Column.bitwiseXOR, words("parity"))  # one word goes with every entry of a list: the parity of 64 cells
    first = sets.join(reps.select("rep"), F.col("doc_id") == F.col("rep"), "left_semi").select(F.col("doc_id").alias("rep"), "n", fold.alias("odd"), "prefix")
    hists = sets.select(F.col("doc_id").alias("rep"), "n", "hist", "parity")  # joined by rep only
    postings = first.select("rep", "n", "odd", F.posexplode("prefix").alias("pos", "token"))
    by = W.partitionBy("token")
    listed = stage(postings.withColumn("of", F.count(F.lit(1)).over(by)).where("of > 1").select("token", "rep", "n", "odd", "of", (F.col("n") - F.col("pos")).alias("left")), "lists")
    linked = lambda df: df.where(den * F.col("both") >= num * (F.col("na") + F.col("nb") - F.col("both")))
    fits = lambda x, y: (F.col(f"{x}.n") * den >= F.col(f"{y}.n") * num) & (F.col(f"{y}.n") * den >= F.col(f"{x}.n") * num) & (F.least(f"{x}.left", f"{y}.left") >= F.ceil(num * (F.col(f"{x}.n") + F.col(f"{y}.n")) / (num + den))) & (F.bit_count(F.col(f"{x}.odd").bitwiseXOR(F.col(f"{y}.odd"))) * (num + den) <= (den - num) * (F.col(f"{x}.n") + F.col(f"{y}.n")))
    order = by.orderBy("n", "rep")
    entry = F.struct("rep", "n", "left", "odd")
    chain = listed.select(entry.alias("x"), F.lag(entry).over(order).alias("y"), F.first(entry).over(order).alias("z"))
    chain = chain.select("x", F.explode(F.array("y", "z")).alias("y")).where(F.col("y.rep") != F.col("x.rep")).where(fits("x", "y"))
    chain = chain.select(F.least("x.rep", "y.rep").alias("a"), F.greatest("x.rep", "y.rep").alias("b")).distinct()
    verified = lambda found: stage(linked(overlaps(docs, stage(at_most(stage(found, "found"), hists).where((num + den) * F.col("most") >= num * (F.col("na") + F.col("nb"))).select("a", "b"), "pairs"), n)).select("a", "b"), "links")
    links = verified(chain)
    comp = stage(components(links), "comp")

    # In a large group of near copies many neighbours are not linked though others are: without these rounds all its linked pairs would be left for the second step.
    crowded = listed.where(F.col("of") >= CROWD)
    for seed in range(0 if crowded.isEmpty() else ROUNDS):
        new = verified(nearest_apart(crowded, comp, num, den, seed))
        if new.isEmpty():
            break
        links = links.union(new)
        comp = stage(components(links), "comp")

    # What may still join two components.
    own = listed.join(small(comp, 200_000), F.col("rep") == F.col("node"), "left").select("token", "rep", "n", "left", "odd", F.coalesce("component", "rep").alias("pivot"))
    ranged = own.withColumn("many", F.min("pivot").over(by) < F.max("pivot").over(by)).where("many")
    block = F.floor(F.log(F.col("n").cast("double")) / np.log(den / num)).cast("int")
    blocks = ranged.withColumn("block", block).groupBy("token", "block", "pivot").agg(F.min("n").alias("n0"), F.max("n").alias("n1"), F.max("left").alias("left"), F.bit_and("odd").alias("all"), F.bit_or("odd").alias("any"))
    ahead = blocks.withColumn("block", F.explode(F.array(F.col("block") - 1, F.col("block"), F.col("block") + 1)))
    x, y = ahead.alias("x"), blocks.alias("y")
    apart = surely_apart(*([F.col(c)] for c in ("x.all", "x.any", "y.all", "y.any")))
    touch = x.join(y, ["token", "block"]).where(F.col("x.pivot") < F.col("y.pivot")).where((F.col("x.n1") * den >= F.col("y.n0") * num) & (F.col("y.n1") * den >= F.col("x.n0") * num))
    touch = touch.where(F.least("x.left", "y.left") >= F.ceil(num * (F.col("x.n0") + F.col("y.n0")) / (num + den))).where(apart * (num + den) <= (den - num) * (F.col("x.n1") + F.col("y.n1")))
    pivots = stage(touch.select(F.col("x.pivot").alias("a"), F.col("y.pivot").alias("b")).distinct(), "pivots")
    n_pivots = pivots.count()
    inside = pivots.select("a").union(pivots.select("b"))
    inside = lit(inside, 2 * n_pivots) if 2 * n_pivots <= 200_000 else inside.distinct()
    members = stage(comp.join(inside, F.col("component") == F.col("a"), "left_semi").where("node <> component").select(F.col("component").alias("a"), F.col("node").alias("b")), "members")
    beyond = stage(overlaps(docs, members, n).select(F.col("b").alias("rep"), F.col("a").alias("pivot"), F.col("nb").alias("n"), (F.col("nb") - F.col("both")).alias("extra")), "beyond")
    alone = hists.join(inside, F.col("rep") == F.col("a"), "left_semi").select("rep", F.col("rep").alias("pivot"), "n", F.lit(0).alias("extra"))
    sides = stage(lit(beyond.union(alone), members.count() + 2 * n_pivots).join(hists.select("rep", "parity"), "rep"), "sides")
    n_sides = sides.count()
    most = lit(stage(fit(sides.groupBy("pivot").agg(F.max("extra").alias("extra"), F.min("n").alias("n"), F.count(F.lit(1)).alias("m")), n_sides), "most"), n_sides)
    p, q = most.alias("p"), most.alias("q")
    close = lambda df, shared: df.join(p, F.col("a") == F.col("p.pivot")).join(q, F.col("b") == F.col("q.pivot")).where(F.col(shared) + F.col("p.extra") + F.col("q.extra") >= F.ceil(num * (F.col("p.n") + F.col("q.n")) / (num + den)))
    met = stage(overlaps(docs, stage(close(at_most(pivots, hists), "most").select("a", "b"), "close"), n), "met")
    more_in_a = F.col("p.m") > F.col("q.m")  # the smaller component is joined first: the last join compares before it makes a row
    near = close(met, "both").select(F.when(more_in_a, F.col("b")).otherwise(F.col("a")).alias("a"), F.when(more_in_a, F.col("a")).otherwise(F.col("b")).alias("b"), "both")
    s, t = sides.alias("s"), sides.alias("t")
    unlike = surely_apart(words("s.parity"), words("s.parity"), words("t.parity"), words("t.parity"))
    s, t = lit(s, n_sides, 20_000), lit(t, n_sides, 20_000)
    open_ = near.join(s, F.col("a") == F.col("s.pivot")).join(t, F.col("b") == F.col("t.pivot")).where((F.col("s.n") * den >= F.col("t.n") * num) & (F.col("t.n") * den >= F.col("s.n") * num) & (F.col("both") + F.col("s.extra") + F.col("t.extra") >= F.ceil(num * (F.col("s.n") + F.col("t.n")) / (num + den))))
    open_ = open_.where(unlike * (num + den) <= (den - num) * (F.col("s.n") + F.col("t.n")))
    more = stage(linked(overlaps(docs, stage(open_.select(F.col("s.rep").alias("a"), F.col("t.rep").alias("b")).distinct(), "open"), n)).select("a", "b"), "more")
    top = stage(components(links.union(more)), "top")
    named = reps.join(small(top, 200_000), F.col("rep") == F.col("node"), "left").select("lo", "hi", F.coalesce("component", "rep").alias("component_id"))
    full = sets.where("n > 0").join(named, ["lo", "hi"]).select("doc_id", F.col("n").cast("long").alias("n_shingles"), "component_id")
    return full.union(sets.where("n = 0").select("doc_id", F.lit(0).cast("long"), "doc_id"))


def drop_near_copies(docs: DataFrame, num: int = 8, den: int = 10, n: int = 5) -> DataFrame:
    """docs without the rows whose component has a smaller id; rows with null id stay."""
    gone = jaccard_classes(docs, num, den, n).where("doc_id <> component_id").select(F.col("doc_id").alias("id"))
    rows, names = hidden(docs)
    return rows.join(gone, F.col(names["doc_id"]).cast("long") == F.col("id"), "left_anti").select(*shown(names))


def op2_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_classes(table(spark, sf_dir, "documents").select("doc_id", "text"), 90, 100, 3)
