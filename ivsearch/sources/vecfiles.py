"""Vector files of the public benchmark sets: fvecs, ivecs and bvecs, read in parallel."""

from __future__ import annotations

import struct

import numpy as np
from pyspark.sql import DataFrame, SparkSession

_KINDS = {"fvecs": ("<f4", 4), "ivecs": ("<i4", 4), "bvecs": ("u1", 1)}


def read(spark: SparkSession, path: str, kind: str | None = None) -> DataFrame:
    """oid (place in the file, by file in the order of paths where there are several), vec. Files may be in any store that Spark reads; each file is one task."""
    kind = kind or path.rsplit(".", 1)[-1]
    dtype, size = _KINDS[kind]

    def run(batches):
        import pyarrow as pa

        for b in batches:
            for path, raw in zip(b.column("path").to_pylist(), b.column("content").to_pylist()):
                if raw:
                    (d,) = struct.unpack_from("<i", raw)
                    rows = np.frombuffer(raw, np.uint8).reshape(-1, 4 + d * size)[:, 4:]
                    v = np.ascontiguousarray(rows).view(dtype).astype(np.float64)
                    for at in range(0, len(v), 4096):
                        part = v[at : at + 4096]
                        yield pa.RecordBatch.from_pydict({"path": [path] * len(part), "oid": pa.array(range(at, at + len(part)), pa.int64()), "vec": pa.array(part.tolist(), pa.list_(pa.float64()))})

    return spark.read.format("binaryFile").load(path).select("path", "content").mapInArrow(run, "path string, oid long, vec array<double>")


def write_rows(vectors: np.ndarray, kind: str = "fvecs") -> bytes:
    dtype, _ = _KINDS[kind]
    head = struct.pack("<i", vectors.shape[1])
    return b"".join(head + np.ascontiguousarray(v, dtype).tobytes() for v in vectors)
