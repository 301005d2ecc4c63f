"""Token ids in a compressed binary form: a context-mixing range coder over independently reset, checksummed blocks."""

from __future__ import annotations

import struct
import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import light_batches, shared_dir, small, table, width
from .tokens import encoder, vocabulary

MAGIC = b"CMR4"
#: Bits of the total of a mixed prediction's frequencies, entries of the order-2 table, steps between two renewals of frequencies and weights.
TOTAL_BITS, PAIR_BITS, RENEW = 26, 18, 64
U = np.uint64
#: A lane's interval is widened by 16 bits whenever it is narrower than this.
NARROW = U(1 << 40)


class Mixer:
    """Predictions of order 0, 1 and 2, blended into one distribution; shared by all lanes of a block, and equal in the coder and the decoder step by step.

    Order 2 and order 1 each predict one id for a context, remembered with a confidence from 0 to 7; order 0 predicts all ids by their adaptive
    frequencies. Each step's distribution is their weighted sum. The weights are learned: for each context of both confidences and of
    whether the two agree, they follow how often order 2, or only order 1, or neither was right there. All sums are integers, so any
    machine decodes alike. Table entries hold an id and, in three bits, its confidence.
    """

    def __init__(self, ids: int):
        self.n, self.bits = ids, max(18, (ids - 1).bit_length() + 2)
        if self.bits > TOTAL_BITS - 3:
            raise ValueError("the vocabulary is too large")
        self.two, self.one = np.zeros(1 << PAIR_BITS, np.int32), np.zeros(ids, np.int32)  # small enough to stay in a core's cache
        self.seen, self.events = np.zeros(ids, np.int64), np.tile(np.array([1, 1, 6], np.int64), (128, 1))
        self.counts = np.zeros(512, np.int64)  # of contexts and of which orders were right, since the last renewal
        self.steps, self.old = 0, 0

    def renew(self, grid: np.ndarray) -> None:
        """Frequencies and weights from the rows of grid so far, at steps 0, 1, 2, 4, ..., 64, 128, 192, ..."""
        t = self.steps
        self.steps += 1
        if t % RENEW and t & (t - 1):
            return
        if t > self.old:
            self.seen += np.bincount(grid[self.old : t].ravel(), minlength=self.n)
        self.old = t
        spare, total = (1 << self.bits) - self.n, int(self.seen.sum())
        freq = 1 + (self.seen * spare // total if total else np.zeros_like(self.seen))
        freq[int(np.argmax(freq))] += (1 << self.bits) - int(freq.sum())
        self.end = np.cumsum(freq)
        self.begin, self.freq = self.end - freq, freq
        self.find = np.repeat(np.arange(self.n, dtype=np.int32), freq)
        none, one, two, both = self.counts.reshape(128, 4).T
        self.events += np.stack([two + both, one, none], 1)
        self.counts[:] = 0
        self.events[self.events.sum(1) > 1 << 16] >>= 1
        np.maximum(self.events, 1, out=self.events)
        two, one, rest = self.events.T
        self.w0 = np.clip((rest << TOTAL_BITS) // (two + one + rest) >> self.bits, 1, (1 << (TOTAL_BITS - self.bits)) - 2)
        left = (1 << TOTAL_BITS) - (self.w0 << self.bits)
        self.w2 = left * two // (two + one)
        self.w1 = left - self.w2

    def predict(self, p1: np.ndarray, p2: np.ndarray) -> None:
        """Takes in the last two ids of each lane."""
        self.at, self.p1 = ((p2 * 0x9E3779B1 + p1 * 0x85EBCA77) >> 11) & ((1 << PAIR_BITS) - 1), p1
        self.e2, self.e1 = self.two.take(self.at), self.one.take(p1)
        self.g2, self.g1 = self.e2 >> 3, self.e1 >> 3
        self.s2, self.s1 = self.e2 & 7, self.e1 & 7
        self.context = ((self.s2 << 4) | (self.s1 << 1) | (self.g1 == self.g2)).astype(np.int64)
        self.a0, self.a1, self.a2 = (w.take(self.context) for w in (self.w0, self.w1, self.w2))

    def place(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Start and frequency of each lane's id x in the blended distribution: an id's interval is its order-0 share and then what the other orders add to it."""
        x32 = x.astype(np.int32)
        self.is2, self.is1 = self.g2 == x32, self.g1 == x32
        start = self.a0 * self.begin.take(x) + self.a2 * (self.g2 < x32) + self.a1 * (self.g1 < x32)
        return start.view(U), (self.a0 * self.freq.take(x) + self.a2 * self.is2 + self.a1 * self.is1).view(U)

    def id_at(self, v: np.ndarray) -> np.ndarray:
        """The id of each lane in whose interval v lies: what the other orders add is taken out, smaller id first, and order 0 looked up."""
        first = self.g1 <= self.g2
        small = np.where(first, self.a1, self.a2)
        for guess, added in ((np.minimum(self.g1, self.g2), small), (np.maximum(self.g1, self.g2), self.a1 + self.a2 - small)):
            v = v - np.minimum(np.maximum(v - (self.a0 * self.end.take(guess) - 1), 0), added)
        return self.find.take(v // self.a0).astype(np.int64)

    def learn(self, x: np.ndarray) -> None:
        """After place(x)."""
        self.counts += np.bincount((self.context << 2) | ((self.is2.view(np.int8) << 1) | self.is1.view(np.int8)), minlength=512)
        new = x.astype(np.int32) << 3
        for held, entry, sure, right, at in ((self.two, self.e2, self.s2, self.is2, self.at), (self.one, self.e1, self.s1, self.is1, self.p1)):
            # A confidence grows by one to 7, or is halved; an id with 1 or 0 gives way.
            then = np.where(right, entry + (sure < 7), entry - ((sure + 1) >> 1))
            np.copyto(then, new, where=(sure <= 1) & ~right)
            held[at] = then  # where lanes share a context, the last one's entry stays


def _lanes(n: int) -> int:
    return max(1, min(8192, n // 512))


def _cut(low: np.ndarray, wide: np.ndarray) -> np.ndarray:
    """wide, with intervals that cross a multiple of 2^48 ended there: their upper 16 bits are settled then, so nothing is ever carried."""
    cross = ((low ^ (low + wide - U(1))) >> U(48)) != 0
    return np.where(cross, (~low + U(1)) & U((1 << 48) - 1), wide) if cross.any() else wide


def encode_block(ids: np.ndarray, vocab: int) -> bytes:
    """One block: magic, count, vocabulary size, crc32 of the ids as little-endian 32-bit, the first four words of each lane, and the other words in the order in which the decoder takes them."""
    n, lanes = len(ids), _lanes(len(ids))
    steps = -(-n // lanes)
    grid = np.zeros(lanes * steps, np.int64)
    grid[:n] = ids
    grid = np.ascontiguousarray(grid.reshape(lanes, steps).T)
    model, every = Mixer(vocab), np.arange(lanes)
    low, wide = np.zeros(lanes, U), np.full(lanes, (1 << 64) - 1, U)
    words, who = [], []
    p1 = p2 = np.zeros(lanes, np.int64)
    for row in grid:
        model.renew(grid)
        model.predict(p1, p2)
        start, freq = model.place(row)
        share = wide >> U(TOTAL_BITS)
        low += start * share
        wide = share * freq
        while len(at := np.flatnonzero(wide < NARROW)):
            x, y = low[at], wide[at]
            words.append((x >> U(48)).astype(np.uint16))
            who.append(at.astype(np.uint16))
            low[at], wide[at] = x << U(16), _cut(x, y) << U(16)
        model.learn(row)
        p1, p2 = row, p1
    events = sum(map(len, who))
    for i in range(4):
        words.append((low >> U(48 - 16 * i)).astype(np.uint16))
        who.append(every.astype(np.uint16))
    # A lane's decoder holds four words at first, and takes the next one each time it widens.
    who, words = np.concatenate(who), np.concatenate(words)
    order = np.argsort(who, kind="stable")
    place = np.empty(len(order), np.int64)
    place[order] = np.arange(len(order))
    words = words[order]
    first = np.concatenate([[0], np.cumsum(np.bincount(who, minlength=lanes))[:-1]])
    parts = words[first[:, None] + np.arange(4)], words[place[:events] + 4]
    return MAGIC + struct.pack("<QII", n, vocab, zlib.crc32(ids.astype("<u4").tobytes())) + b"".join(x.astype("<u2").tobytes() for x in parts)


def decode_block(data: bytes) -> np.ndarray:
    """The ids of a block; ValueError if it is damaged."""
    if data[:4] != MAGIC:
        raise ValueError("not a block of token ids")
    n, vocab, crc = struct.unpack_from("<QII", data, 4)
    lanes = _lanes(n)
    steps = -(-n // lanes)
    words, at = np.frombuffer(data, "<u2", offset=20).astype(U), 4 * lanes
    model = Mixer(vocab)
    low, wide, code = np.zeros(lanes, U), np.full(lanes, (1 << 64) - 1, U), np.zeros(lanes, U)
    for i in range(4):
        code = (code << U(16)) | words[i : 4 * lanes : 4]
    grid = np.zeros((steps, lanes), np.int64)
    p1 = p2 = np.zeros(lanes, np.int64)
    for row in grid:
        model.renew(grid)
        model.predict(p1, p2)
        share = wide >> U(TOTAL_BITS)
        row[:] = model.id_at(np.minimum((code - low) // np.maximum(share, U(1)), U((1 << TOTAL_BITS) - 1)).view(np.int64))
        start, freq = model.place(row)
        low += start * share
        wide = share * freq
        while len(who := np.flatnonzero(wide < NARROW)):
            x, new = low[who], words[at : at + len(who)]
            if len(new) < len(who):
                raise ValueError("a block of token ids is damaged")
            at += len(who)
            wide[who], low[who], code[who] = _cut(x, wide[who]) << U(16), x << U(16), (code[who] << U(16)) | new
        model.learn(row)
        p1, p2 = row, p1
    ids = grid.T.reshape(-1)[:n]
    if zlib.crc32(ids.astype("<u4").tobytes()) != crc:
        raise ValueError("a block of token ids is damaged")
    return ids


def write(docs: DataFrame, out: str, path: str | None = None, end_id: int | None = 2, block_ids: int = 1 << 22) -> None:
    """Writes the ids of all texts of docs (doc_id, text), in ascending order of doc_id, to out: one row of a Parquet table per block.

    A row holds part and block (their order), the documents' ids and numbers of token ids, and the coded block of all their ids. Documents are
    dealt by ranges of doc_id, rows of one id by ranges of a hash of the text, so no id can fill a task; blocks end between documents once they hold block_ids ids.
    Null text is empty; null doc_id comes first; rows of one id come in the order of that hash. Extra columns are ignored; an empty table gives an empty one.
    """
    path, end = path or vocabulary(), np.array([] if end_id is None else [end_id], "<u4").tobytes()
    kind = "part int, block int, n_ids long, n_null int, docs binary, sizes binary, data binary"
    schema = pa.schema([("part", pa.int32()), ("block", pa.int32()), ("n_ids", pa.int64()), ("n_null", pa.int32()), ("docs", pa.binary()), ("sizes", pa.binary()), ("data", pa.binary())])

    def run(batches):
        from pyspark import TaskContext

        enc, part, block = encoder(path), TaskContext.get().partitionId(), 0

        def flush(docs_, parts):
            nonlocal block
            ids = np.frombuffer(b"".join(parts), "<u4")
            known = np.array([d for d in docs_ if d is not None], "<i8").tobytes()
            sizes = np.array([len(p) // 4 for p in parts], "<u4").tobytes()
            row = {"part": part, "block": block, "n_ids": len(ids), "n_null": sum(d is None for d in docs_), "docs": zlib.compress(known), "sizes": zlib.compress(sizes), "data": encode_block(ids, len(enc.opens))}
            block += 1
            return pa.RecordBatch.from_pylist([row], schema=schema)

        docs_, parts, size = [], [], 0
        for doc, ids in enc.rows(batches):
            docs_.append(doc)
            parts.append(ids + end)
            size += len(parts[-1]) // 4
            if size >= block_ids:
                yield flush(docs_, parts)
                docs_, parts, size = [], [], 0
        enc.forget()
        if docs_:
            yield flush(docs_, parts)

    light_batches(docs.sparkSession)
    # Rows that repeat an id and a text as well are dealt by their place in the input: they are alike, so any order of them is the same.
    order = ["doc_id", "h", "at"]
    keyed = docs.select(F.col("doc_id").cast("long"), "text", F.xxhash64("text").alias("h"), F.monotonically_increasing_id().alias("at"))
    dealt = keyed.repartitionByRange(width(docs.sparkSession), *order).sortWithinPartitions(*order)
    dealt.select("doc_id", "text").mapInArrow(run, kind).write.parquet(out)


def read(spark: SparkSession, at: str, with_ids: bool = True) -> DataFrame:
    """Documents of files that write() made: doc_id, start (ids of all documents before it), n_tokens, ids_crc32, ids (array<int>, unless with_ids is false).

    Blocks are decoded independently; a damaged one fails the query. First ids of blocks come from running sums, over the parts and inside each.
    """
    files = spark.read.parquet(at)
    kind = "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<int>" * with_ids

    def run(batches):
        for batch in batches:
            for r in batch.to_pylist():
                ids = decode_block(r["data"]).astype("<u4")
                docs = np.frombuffer(zlib.decompress(r["docs"]), "<i8")
                n = np.frombuffer(zlib.decompress(r["sizes"]), "<u4").astype(np.int64)
                ends = np.concatenate([[0], np.cumsum(n)])
                raw = memoryview(ids.tobytes())
                crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(ends.tolist(), ends[1:].tolist())]
                known = pa.concat_arrays([pa.nulls(r["n_null"], pa.int64()), pa.array(docs)])
                cols = [known, pa.array(ends[:-1] + r["first"]), pa.array(n), pa.array(crc, pa.int64())]
                if with_ids:
                    cols.append(pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(ids.astype(np.int32))))
                yield pa.RecordBatch.from_arrays(cols, [c.split()[0] for c in kind.split(", ")])

    light_batches(spark)
    parts = files.groupBy(F.col("part").alias("p")).agg(F.sum("n_ids").alias("n"))
    before = parts.select("p", (F.sum("n").over(W.orderBy("p")) - F.col("n")).alias("before"))  # one row a part
    index = files.select(F.col("part").alias("p"), F.col("block").alias("b"), (F.sum("n_ids").over(W.partitionBy("part").orderBy("block")) - F.col("n_ids")).alias("own"))
    first = index.join(before, "p").select("p", "b", (F.col("own") + F.col("before")).alias("first"))
    placed = files.join(small(first), (F.col("part") == F.col("p")) & (F.col("block") == F.col("b"))).select("n_null", "docs", "sizes", "data", "first")
    return placed.mapInArrow(run, kind)


def op8_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = f"{shared_dir(spark)}/tokens-{uuid.uuid4().hex}"
    write(table(spark, sf_dir, "documents").select("doc_id", "text"), out)
    return read(spark, out, with_ids=False)
