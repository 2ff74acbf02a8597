"""Letter words of whole batches of texts as hashes with their places, from UTF-8 bytes."""

from __future__ import annotations

import numpy as np

from narrative_engine.llm.shingles import _ODD, _POWERS, _VALUE, mix

#: Letters and digits of ASCII and every byte of a longer character belong to words.
_WORD = np.zeros(256, dtype=bool)
_WORD[[*range(48, 58), *range(65, 91), *range(97, 123)]] = True
_WORD[128:] = True
_END = np.zeros(256, dtype=bool)
_END[[ord(c) for c in ".!?\n"]] = True


def spans(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First and past-the-last byte of every word."""
    if not len(data):
        return np.empty(0, dtype=np.int64), np.empty(0, dtype=np.int64)
    edge = np.flatnonzero(np.diff(np.concatenate(([False], _WORD[data], [False])).astype(np.int8)))
    return edge[::2], edge[1::2]


def sums(data: np.ndarray) -> np.ndarray:
    _POWERS.upto(len(data) + 1)
    out = np.zeros(len(data) + 1, dtype=np.uint64)
    np.cumsum(_VALUE[data] * _POWERS.up[: len(data)], out=out[1:])
    return out


def hashed(total: np.ndarray, first: np.ndarray, last: np.ndarray, kind: int = 0) -> np.ndarray:
    """Hashes of the byte spans; ``kind`` keeps feature families apart."""
    return mix((total[last] - total[first]) * _POWERS.down[first] + (last - first + (kind << 20)).astype(np.uint64) * _ODD)


def word_hashes(data: np.ndarray) -> np.ndarray:
    first, last = spans(data)
    return hashed(sums(data), first, last) if len(first) else np.empty(0, dtype=np.uint64)


def sentence_of(data: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Number of the sentence in which each word starts; sentences without words get none."""
    raw = np.cumsum(_END[data])[first]
    return np.cumsum(np.concatenate(([0], np.diff(raw) > 0))) if len(raw) else raw
