"""Packing documents into fixed windows by multiway differencing."""

from __future__ import annotations

import heapq
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import light_batches, table
from .tokens import encoder, vocabulary


def difference(sizes: list[int], k: int) -> list[list[int]]:
    """k parts of the indexes of sizes, with near-equal sums: the two partial partitions with the widest spread are merged, largest part onto smallest, until one is left.

    A partial partition is the descending sums of its parts that are not empty, and for each part a node of a binary tree
    whose leaves are the indexes.
    """
    tree: list[tuple[int, int]] = []
    n = len(sizes)
    heap = [(-s, i, np.array([s]), np.array([i])) for i, s in enumerate(sizes)]
    heapq.heapify(heap)
    tie = n
    while len(heap) > 1:
        _, _, s1, t1 = heapq.heappop(heap)
        _, _, s2, t2 = heapq.heappop(heap)
        over = max(0, len(s1) + len(s2) - k)
        if over:
            # The last `over` parts of the first meet the last `over` of the second, smallest with largest of those.
            a, b = len(s1) - over, len(s2) - over
            both = s1[a:] + s2[b:][::-1]
            nodes = np.arange(n + len(tree), n + len(tree) + over)
            tree.extend(zip(t1[a:].tolist(), t2[b:][::-1].tolist()))
            s, t = np.concatenate([s1[:a], s2[:b], both]), np.concatenate([t1[:a], t2[:b], nodes])
        else:
            s, t = np.concatenate([s1, s2]), np.concatenate([t1, t2])
        order = np.argsort(-s, kind="stable")
        s, t = s[order], t[order]
        heapq.heappush(heap, (-int(s[0] - (s[-1] if len(s) == k else 0)), tie, s, t))
        tie += 1
    out = []
    for root in heap[0][3].tolist() if heap else []:
        stack, part = [root], []
        while stack:
            x = stack.pop()
            if x < n:
                part.append(x)
            else:
                stack.extend(tree[x - n])
        out.append(sorted(part))
    return out


def windows(sizes: list[int], capacity: int) -> list[list[int]]:
    """Parts of the indexes of sizes, none with a sum above capacity: the fewest windows that could do, and more while one is exceeded."""
    k = max(1, -(-sum(sizes) // capacity))
    while True:
        parts = difference(sizes, k)
        if all(sum(sizes[i] for i in p) <= capacity for p in parts):
            return parts
        k += max(1, k // 200)


def pack(docs: DataFrame, path: str | None = None, capacity: int = 1024, end_id: int | None = 0, group: int = 512, cut: int = 256) -> DataFrame:
    """Pieces of documents in windows: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, ids (array<int>).

    Each document is tokenized whole and ends with end_id. It fills whole windows of its own as far as it goes; what is left, under
    capacity, is cut into pieces of at most cut ids, and the pieces of up to group documents of one input partition are packed by
    differencing, a batch at a time: no shuffle, and memory for one batch. The last batch of a partition may leave a
    window unfilled. sequence_id is the partition's number times 2^33 plus a count, so a task run again gives the same rows.
    Null and empty texts are the end id alone. Rows that repeat an id are packed each for itself; null ids stay null.
    """
    path, end = path or vocabulary(), np.array([] if end_id is None else [end_id], "<u4").tobytes()

    def run(batches):
        from pyspark import TaskContext

        enc, count = encoder(path), TaskContext.get().partitionId() << 33
        names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]

        def flush(whole, rest):
            nonlocal count
            rows = []
            for doc, start, ids, total in whole:
                rows.append((doc, start, len(ids) // 4, zlib.crc32(ids), total, count, 0, ids))
                count += 1
            for part in windows([len(x[2]) // 4 for x in rest], capacity) if rest else []:
                at = 0
                for i in part:
                    doc, start, ids, total = rest[i]
                    rows.append((doc, start, len(ids) // 4, zlib.crc32(ids), total, count, at, ids))
                    at += len(ids) // 4
                count += 1
            cols = list(zip(*rows))
            ids = pa.array(np.frombuffer(b"".join(cols[7]), "<i4"), pa.int32())
            ends = np.concatenate([[0], np.cumsum(np.array(cols[2]))]).astype(np.int32)
            return pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in cols[:7]), pa.ListArray.from_arrays(pa.array(ends), ids)], [*names, "ids"])

        whole, rest, n = [], [], 0
        for doc, ids in enc.rows(batches):
            ids += end
            total = len(ids) // 4
            full = total - total % capacity
            whole += [(doc, s, ids[4 * s : 4 * (s + capacity)], total) for s in range(0, full, capacity)]
            left = total - full
            k = -(-left // cut)
            edges = [full + left * i // k for i in range(k + 1)] if k else []
            rest += [(doc, a, ids[4 * a : 4 * b], total) for a, b in zip(edges, edges[1:])]
            n += 1
            if n >= group or len(whole) > 4096:
                yield flush(whole, rest)
                whole, rest, n = [], [], 0
        if whole or rest:
            yield flush(whole, rest)
        enc.forget()

    light_batches(docs.sparkSession)
    return docs.selectExpr("cast(doc_id as bigint) doc_id", "text").mapInArrow(run, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, ids array<int>")


def op3_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents").select("doc_id", "text")).drop("ids")
