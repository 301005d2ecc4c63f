"""Named numpy arrays in one binary value: what a shard's task reads without making Python objects of it."""

from __future__ import annotations

import json
import struct

import numpy as np


def pack(**arrays: np.ndarray) -> bytes:
    parts = {k: np.ascontiguousarray(a) for k, a in arrays.items()}
    head = json.dumps([[k, a.dtype.str, a.shape] for k, a in parts.items()]).encode()
    head += b" " * (-(len(head) + 4) % 8)
    return struct.pack("<I", len(head)) + head + b"".join(a.tobytes() + bytes(-a.nbytes % 8) for a in parts.values())


def unpack(data: bytes) -> dict[str, np.ndarray]:
    (n,) = struct.unpack_from("<I", data)
    at, out = 4 + n, {}
    for name, kind, shape in json.loads(data[4:at]):
        count = int(np.prod(shape))
        out[name] = np.frombuffer(data, kind, count, at).reshape(shape)
        at += out[name].nbytes + -out[name].nbytes % 8
    return out
