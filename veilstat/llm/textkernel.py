"""Vectorised words and word hashes over the raw bytes of a batch of texts.

Words are maximal runs of bytes other than ASCII white space; these bytes never occur
inside a multi-byte UTF-8 character, so byte positions are safe word boundaries.
"""

from __future__ import annotations

import numpy as np

_IS_WORD = np.ones(256, dtype=bool)
_IS_WORD[[32, 9, 10, 11, 12, 13]] = False
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit splittable generator; a bijection of uint64."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_STEP = np.uint64(0x9E3779B97F4A7C15)


def stream(n: int, seed: int) -> np.ndarray:
    """n pseudo-random uint64 that depend on position and seed alone."""
    with np.errstate(over="ignore"):
        return mix(np.arange(1, n + 1, dtype=np.uint64) * _STEP + np.uint64(seed))


_BYTE = stream(256, 11)
_BYTE[~_IS_WORD] = 0
_PLACE = stream(4096, 23) | np.uint64(1)


def _places(longest: int) -> np.ndarray:
    return _PLACE[:longest] if longest <= len(_PLACE) else stream(longest, 23) | np.uint64(1)


def words(data: np.ndarray, offsets: np.ndarray, lower: bool = False, hashes: bool = True):
    """(row, start, end, hash) of every word; rows are given by ``offsets``."""
    n = len(data)
    none = np.zeros(0, np.int64)
    if not n:
        return none, none, none, np.zeros(0, np.uint64)
    if lower:
        data = _LOWER[data]
    inside = _IS_WORD[data]
    starts, ends = inside.copy(), inside.copy()
    starts[1:] &= ~inside[:-1]
    ends[:-1] &= ~inside[1:]
    first = offsets[:-1][offsets[:-1] < n]
    last = offsets[1:][offsets[1:] > 0] - 1
    starts[first] = inside[first]
    ends[last] = inside[last]
    s, e = np.flatnonzero(starts), np.flatnonzero(ends) + 1
    row = np.searchsorted(offsets[1:], s, side="right")
    if not hashes or not len(s):
        return row, s, e, np.zeros(0, np.uint64)
    base = s[0]
    spans = np.diff(s, append=n)
    place = np.arange(base, n) - np.repeat(s, spans)
    longest = int(spans.max())
    h = np.add.reduceat(_BYTE[data[base:]] * _places(longest)[place], s - base)
    return row, s, e, mix(h + (e - s).astype(np.uint64) * _STEP)


_ORDER = stream(64, 37) | np.uint64(1)


def grams(row: np.ndarray, h: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(index of first word, hash) of every run of k words that stays in one row."""
    if len(h) < k:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    at = np.flatnonzero(row[: len(row) - k + 1] == row[k - 1 :])
    total = np.zeros(len(h) - k + 1, dtype=np.uint64)
    weights = _ORDER if k <= len(_ORDER) else stream(k, 37) | np.uint64(1)
    for i in range(k):
        total += h[i : len(h) - k + 1 + i] * weights[i]
    return at, mix(total[at])
