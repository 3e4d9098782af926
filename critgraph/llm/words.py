"""Words, word hashes and rolling shingle hashes of whole texts, for Python workers.

Words are hashed without making them: a text's bytes are mapped to 64-bit values, a
prefix sum of value * r^place (mod 2^64) gives each word's polynomial by one difference,
and the place is taken out with the inverse power of r.
"""

from __future__ import annotations

import numpy as np

_R = 0x9E3779B97F4A7C15 | 1
_R_INVERSE = pow(_R, -1, 1 << 64)
_MUL = np.uint64(0xD6E8FEB86659FD93)
_VALUES = np.random.default_rng(20240229).integers(0, 1 << 64, 256, dtype=np.uint64)
_SPACE = np.zeros(256, bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True
_BLOCK = 1 << 16


def _powers(base: int) -> np.ndarray:
    out = np.empty(_BLOCK + 1, np.uint64)
    x = 1
    for i in range(_BLOCK + 1):
        out[i] = x
        x = x * base & (2**64 - 1)
    return out


_UP, _DOWN = _powers(_R), _powers(_R_INVERSE)


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * _MUL
    return h ^ (h >> np.uint64(29))


def power(table: np.ndarray, at: np.ndarray) -> np.ndarray:
    """base^at for ascending places of any size, from the table of powers below _BLOCK."""
    if not len(at) or at[-1] < _BLOCK:
        return table[at]
    low, high = at % _BLOCK, at // _BLOCK
    steps = np.ones(int(high[-1]) + 1, np.uint64)
    for i in range(1, len(steps)):
        steps[i : i + 1] = steps[i - 1 : i] * table[_BLOCK]
    return table[low] * steps[high]


def word_bounds(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs of bytes that are no white space (code 9-13 or 32)."""
    solid = ~_SPACE[raw]
    edge = np.flatnonzero(solid[1:] != solid[:-1]) + 1
    if solid[0]:
        edge = np.concatenate(([0], edge))
    if solid[-1]:
        edge = np.concatenate((edge, [len(raw)]))
    return edge[::2], edge[1::2]


def word_hashes(text: bytes) -> np.ndarray:
    """A 64-bit hash of each word, in order."""
    raw = np.frombuffer(text, np.uint8)
    if not len(raw):
        return np.empty(0, np.uint64)
    start, end = word_bounds(raw)
    sums = np.zeros(len(raw) + 1, np.uint64)
    np.cumsum(_VALUES[raw] * (_UP[: len(raw)] if len(raw) <= _BLOCK else power(_UP, np.arange(len(raw)))), out=sums[1:])
    return _mixed((sums[end] - sums[start]) * power(_DOWN, start) + (end - start).astype(np.uint64))


def rolling(h: np.ndarray, k: int) -> np.ndarray:
    """Hash of each run of ``k`` consecutive word hashes; of the whole sequence if it is shorter (but not empty)."""
    if not len(h):
        return h
    k = min(k, len(h))
    n = len(h) - k + 1
    out = np.full(n, k, np.uint64)
    for j in range(k):
        out = (out ^ h[j : j + n]) * _MUL
        out ^= out >> np.uint64(29)
    return out


def distinct(h: np.ndarray) -> np.ndarray:
    """Sorted distinct values."""
    s = np.sort(h)
    if len(s) < 2:
        return s
    return s[np.concatenate(([True], s[1:] != s[:-1]))]
