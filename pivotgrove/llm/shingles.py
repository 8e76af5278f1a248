"""Word shingles as 64-bit hashes, by array arithmetic over a text's bytes.

A word's hash is the sum of its bytes' random values, each times a power of an odd base that counts from the
word's start (differences of one running sum, times the inverse power of its place); four or five words'
hashes are weighed by their place in the shingle, summed and mixed. Words are runs of bytes other than ASCII
white space, A to Z lower-cased.
"""

from __future__ import annotations

import numpy as np

_BASE = 0x9E3779B97F4A7C15 | 1
_MASK = (1 << 64) - 1
_VALUE = np.random.default_rng(20240229).integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_VALUE[65:91] = _VALUE[97:123]
_LOWER = np.arange(256)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[32, *range(9, 14)]] = True
_PLACE = np.random.default_rng(20240301).integers(1, 1 << 63, 64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_powers = [np.ones(1, dtype=np.uint64), np.ones(1, dtype=np.uint64)]


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers 0 to n of the base and of its inverse modulo 2 to the 64th."""
    if len(_powers[0]) <= n:
        size = 1 << max(16, n.bit_length())
        inverse = pow(_BASE, -1, 1 << 64)
        for i, base in enumerate((_BASE, inverse)):
            steps = np.full(size, base, dtype=np.uint64)
            steps[0] = 1
            _powers[i] = np.multiply.accumulate(steps)
    return _powers[0], _powers[1]


def mix(x: np.ndarray) -> np.ndarray:
    """A finaliser that spreads every bit (the public splitmix64 constants)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def word_bounds(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    inside = np.concatenate(([False], ~_SPACE[raw], [False]))
    edge = np.flatnonzero(inside[1:] != inside[:-1])
    return edge[::2], edge[1::2]


def endings_at(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A number made of the last three bytes of each word, lower-cased."""
    out = np.zeros(len(starts), dtype=np.uint64)
    for back in (1, 2, 3):
        at = ends - back
        out = out << np.uint64(8) | np.where(at >= starts, _LOWER[raw[np.maximum(at, 0)]], 0).astype(np.uint64)
    return out


def word_hashes(text: str | bytes) -> np.ndarray:
    raw = np.frombuffer(text.encode() if isinstance(text, str) else text, dtype=np.uint8)
    if not len(raw):
        return np.empty(0, dtype=np.uint64)
    return hashes_at(raw, *word_bounds(raw))


def hashes_at(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    up, down = _power(len(raw))
    running = np.zeros(len(raw) + 1, dtype=np.uint64)
    np.cumsum(_VALUE[raw] * up[: len(raw)], out=running[1:])
    return mix((running[ends] - running[starts]) * down[starts] + (ends - starts).astype(np.uint64))


def shingle_hashes(text: str | bytes, words: int) -> np.ndarray:
    """The distinct shingles of a whole text, ascending; with fewer words, the whole sequence as one."""
    w = word_hashes(text)
    if not len(w):
        return w
    k = min(words, len(w))
    total = np.full(len(w) - k + 1, k, dtype=np.uint64)
    for i in range(k):
        total += w[i : len(w) - k + 1 + i] * _PLACE[i]
    return np.unique(mix(total))
