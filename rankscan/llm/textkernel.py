"""Vectorised text primitives on UTF-8 bytes: word spans, 64-bit word hashes, shingle sets."""

from __future__ import annotations

import numpy as np
import pyarrow as pa

_U = np.uint64
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
#: Powers for longer texts are made for each anew.
KEEP_POWERS = 1 << 20
_POWERS = [np.ones(1, _U), np.ones(1, _U)]

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: Bytes that part words: white space of ASCII.
SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
#: Bytes that part words: all of ASCII but digits and letters.
NON_WORD = np.zeros(256, bool)
NON_WORD[:128] = True
NON_WORD[48:58] = NON_WORD[65:91] = NON_WORD[97:123] = False


def _powers(n: int) -> list[np.ndarray]:
    """Powers of the base and of its inverse; those for texts of up to KEEP_POWERS bytes are kept."""
    powers = list(_POWERS)
    if len(_POWERS[0]) < n:
        size = max(n, 1 << 16)
        for k, base in enumerate((_BASE, _INVERSE)):
            steps = np.full(size, base, _U)
            steps[0] = 1
            powers[k] = np.multiply.accumulate(steps)
        if size <= KEEP_POWERS:
            _POWERS[:] = powers
    return powers


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit integers."""
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def spans(buf: np.ndarray, breaks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of bytes that are no breaks."""
    flags = np.ones(len(buf) + 2, np.int8)
    flags[1:-1] = breaks[buf]
    edges = np.flatnonzero(flags[1:] != flags[:-1])
    return edges[::2], edges[1::2]


class Hashed:
    """Prefix sums over a text from which any span's polynomial hash follows in O(1)."""

    def __init__(self, buf: np.ndarray):
        power, self.inverse = _powers(len(buf) + 1)
        self.sums = np.zeros(len(buf) + 1, _U)
        np.cumsum((buf.astype(_U) + _U(1)) * power[: len(buf)], out=self.sums[1:])

    def spans(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        return mix((self.sums[ends] - self.sums[starts]) * self.inverse[starts] + (ends - starts).astype(_U))


def sequences(words: np.ndarray, k: int) -> np.ndarray:
    """Hashes of all runs of k words; of the whole sequence if it is shorter."""
    k_now = min(k, len(words))
    if not k_now:
        return np.zeros(0, _U)
    out = np.full(len(words) - k_now + 1, k_now, _U)
    for j in range(k_now):
        out = out * _U(0xD6E8FEB86659FD93) + words[j : len(words) - k_now + 1 + j]
    return mix(out)


def shingle_set(buf: np.ndarray, k: int, breaks: np.ndarray = SPACE) -> np.ndarray:
    """Sorted distinct hashes of a text's k-word shingles, A-Z lower-cased."""
    low = LOWER[buf]
    starts, ends = spans(low, breaks)
    if not len(starts):
        return np.zeros(0, _U)
    return np.unique(sequences(Hashed(low).spans(starts, ends), k))


def texts(column: pa.Array):
    """Each row's bytes without copying; null counts as empty."""
    column = column.cast(pa.large_string()) if not pa.types.is_large_string(column.type) else column
    at = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(column.buffers()[2], np.uint8) if column.buffers()[2] is not None else np.zeros(0, np.uint8)
    valid = column.is_valid().to_numpy(zero_copy_only=False)
    for ok, a, b in zip(valid.tolist(), at[:-1].tolist(), at[1:].tolist()):
        yield data[a:b] if ok else data[:0]
