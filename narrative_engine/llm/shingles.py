"""Shingle sets of whole batches of texts, straight from their UTF-8 bytes.

Words are runs of bytes outside a table of separators; their hashes are differences of running
sums, so no Python string is made.  A shingle's hash is 64 bits wide.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

_RNG = np.random.default_rng(20_240_501)
_ODD = np.uint64(0x9E3779B97F4A7C15)
_BLANK = np.zeros(256, dtype=bool)
_BLANK[[0x20, *range(0x09, 0x0E)]] = True
_VALUE = _RNG.integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_VALUE[65:91] = _VALUE[97:123]  # A-Z count as a-z
_STEP = np.uint64(0xD6E8FEB86659FD93)


def _inverse(x: int) -> int:
    return pow(x, -1, 1 << 64)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every bit."""
    x = x.copy()
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


class _Powers:
    """Powers of the step and of its inverse, grown as texts ask for them."""

    def __init__(self) -> None:
        self.up = self.down = np.ones(1, dtype=np.uint64)

    def upto(self, n: int) -> None:
        if len(self.up) < n:
            n = max(n, 2 * len(self.up))
            for name, base in (("up", int(_STEP)), ("down", _inverse(int(_STEP)))):
                p = np.full(n, base, dtype=np.uint64)
                p[0] = 1
                setattr(self, name, np.multiply.accumulate(p))


_POWERS = _Powers()


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and where each row starts; nulls are empty."""
    if pa.types.is_large_string(column.type):
        column = column.cast(pa.string())
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = column.buffers()[2]
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None else np.empty(0, dtype=np.uint8)
    return raw, offsets


def words(data: np.ndarray) -> np.ndarray:
    """A hash for every word of one text."""
    if not len(data):
        return np.empty(0, dtype=np.uint64)
    blank = _BLANK[data]
    edge = np.flatnonzero(np.diff(np.concatenate(([True], blank, [True])).astype(np.int8)))
    first, last = edge[::2], edge[1::2]
    if not len(first):
        return np.empty(0, dtype=np.uint64)
    _POWERS.upto(len(data) + 1)
    sums = np.empty(len(data) + 1, dtype=np.uint64)
    sums[0] = 0
    np.cumsum(_VALUE[data] * _POWERS.up[: len(data)], out=sums[1:])
    return mix((sums[last] - sums[first]) * _POWERS.down[first] + (last - first).astype(np.uint64) * _ODD)


def shingle_set(data: np.ndarray, size: int = 4) -> np.ndarray:
    """Sorted different hashes of the text's shingles; fewer words make one shingle, none make none."""
    w = words(data)
    if not len(w):
        return w
    k = min(size, len(w))
    n = len(w) - k + 1
    h = np.full(n, k, dtype=np.uint64)
    for i in range(k):
        h = mix(h * _ODD + w[i : i + n])
    return np.unique(h)


def sets(column: pa.Array, size: int = 4) -> list[np.ndarray]:
    raw, at = text_bytes(column)
    return [shingle_set(raw[a:b], size) for a, b in zip(at[:-1], at[1:])]
