"""Words of UTF-8 texts as hashed numpy streams; nothing is made per word in Python."""
from __future__ import annotations

import numpy as np

_RNG = np.random.default_rng(20240229)
_SPACE = np.zeros(256, bool)
_SPACE[[32, *range(9, 14)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_BYTE = _RNG.integers(1, 1 << 63, 256, dtype=np.uint64) | np.uint64(1)
_POWER = np.cumprod(np.full(256, 0x9E3779B97F4A7C15 | 1, np.uint64), dtype=np.uint64)


def mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def power(at: np.ndarray) -> np.ndarray:
    """Odd multipliers by place in a word; places over 255 take theirs from two tables, so words may be of any length."""
    if len(at) and at.max() > 255:
        return _POWER[at & 255] * mix((at >> 8).astype(np.uint64) + np.uint64(7)) | np.uint64(1)
    return _POWER[at]


def words(raw: bytes, space: np.ndarray = _SPACE, fold: np.ndarray = _LOWER) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hash, start, end) of every maximal run of bytes outside space, folded bytewise."""
    b = np.frombuffer(raw, np.uint8)
    none = np.zeros(0, np.int64)
    inside = ~space[b]
    edge = np.flatnonzero(np.diff(inside.view(np.int8), prepend=np.int8(0), append=np.int8(0)))
    start, end = edge[::2], edge[1::2]
    if not len(start):
        return none.astype(np.uint64), none, none
    kept = np.flatnonzero(inside)
    size = end - start
    at = np.arange(len(kept)) - np.repeat(np.cumsum(size) - size, size)
    h = np.add.reduceat(_BYTE[fold[b[kept]]] * power(at), np.cumsum(size) - size)
    return mix(h + size.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)), start, end


def windows(h: np.ndarray, n: int) -> np.ndarray:
    """Hashes of the windows of n consecutive words."""
    if len(h) < n:
        return np.zeros(0, np.uint64)
    m = len(h) - n + 1
    out = np.zeros(m, np.uint64)
    for i in range(n):
        out = (out ^ (out >> np.uint64(29))) * np.uint64(0xFF51AFD7ED558CCD) + h[i : i + m]
    return mix(out)
