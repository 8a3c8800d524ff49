"""Hashes of runs of words, sliding minima, and compact blocks of sorted numbers."""

from __future__ import annotations

import numpy as np
import zstandard

_MIX, _END = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9)


def grams(a: np.ndarray, k: int, at: np.ndarray | None = None) -> np.ndarray:
    """A 64-bit hash of each run of k word hashes, or of those that start ``at`` given places."""
    n = len(a) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    if at is not None and 3 * len(at) > n:
        return grams(a, k)[at]
    out = np.zeros(n if at is None else len(at), np.uint64)
    for i in range(k):
        out *= _MIX
        out += a[i : i + n] if at is None else a[at + i]
    out ^= out >> np.uint64(29)
    out *= _END
    out ^= out >> np.uint64(32)
    return out


def sliding_min(a: np.ndarray, w: int) -> np.ndarray:
    """The minimum of each w neighbours, by doubling."""
    n, step = len(a) - w + 1, 1
    if n <= 0:
        return a[:0]
    while step * 2 <= w:
        a, step = np.minimum(a[:-step], a[step:]), step * 2
    return np.minimum(a[:n], a[w - step : w - step + n]) if step < w else a[:n]


def pack(ascending: np.ndarray, *others: np.ndarray) -> bytes:
    """Columns of 64-bit numbers of one length, the first ascending: differences, byte planes, zstd."""
    steps = np.diff(ascending, prepend=ascending.dtype.type(0))
    planes = [np.ascontiguousarray(x).view(np.uint8).reshape(-1, 8).T.tobytes() for x in (steps, *others)]
    return zstandard.compress(b"".join(planes), 1)


def unpack(block: bytes, columns: int) -> list[np.ndarray]:
    """What ``pack`` was given: the first column unsigned, the others signed."""
    planes = np.frombuffer(zstandard.decompress(block), np.uint8).reshape(columns, 8, -1)
    out = [np.ascontiguousarray(p.T).reshape(-1).view(np.int64) for p in planes]
    return [np.cumsum(out[0].view(np.uint64), dtype=np.uint64), *out[1:]]
