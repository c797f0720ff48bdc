"""Hash shuffles in packed form: many small keys of one slice of text travel as one row.

A slice sends each hash partition one row: the low bits of its hashes, where they stand,
and the documents they stand in. That is a few bytes a hash instead of a row's overhead.
"""

from __future__ import annotations

import numpy as np
import zstandard

_PACK = None


def squeeze(*arrays: np.ndarray) -> bytes:
    """Arrays as one compressed value; increasing uint32 arrays should come as differences."""
    global _PACK
    if _PACK is None:
        _PACK = zstandard.ZstdCompressor(level=1)
    head = np.array([len(arrays), *[len(a) for a in arrays]], dtype="<u4").tobytes()
    kinds = bytes(ord(a.dtype.char) for a in arrays)
    return _PACK.compress(head + kinds + b"".join(a.tobytes() for a in arrays))


def unsqueeze(raw: bytes) -> list[np.ndarray]:
    data = zstandard.ZstdDecompressor().decompress(raw)
    n = int(np.frombuffer(data, "<u4", 1)[0])
    sizes = np.frombuffer(data, "<u4", n, 4).tolist()
    kinds = data[4 + 4 * n : 4 + 5 * n].decode()
    out, at = [], 4 + 5 * n
    for size, kind in zip(sizes, kinds, strict=True):
        dtype = np.dtype(kind)
        out.append(np.frombuffer(data, dtype, size, at))
        at += size * dtype.itemsize
    return out


def gaps(places: np.ndarray) -> np.ndarray:
    """Differences of increasing places, in 16 bits where they fit."""
    d = np.diff(places, prepend=0)
    return d.astype(np.uint16 if not len(d) or d.max() < 65536 else np.uint32)


def first_of(values: np.ndarray, *others: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order, starts): a stable order by value and the starts of equal runs in it."""
    order = np.argsort(values, kind="stable")
    v = values[order]
    starts = np.flatnonzero(np.concatenate(([True], v[1:] != v[:-1]))) if len(v) else np.zeros(0, np.int64)
    return order, starts
