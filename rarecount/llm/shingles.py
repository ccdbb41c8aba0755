"""Five-word shingle sets of texts and their min-wise signatures, in numpy."""

from __future__ import annotations

import numpy as np
from xxhash import xxh3_64_intdigest

WORDS = 5
_P = np.uint64(0x9E3779B97F4A7C15)
_Q = np.uint64(0xD6E8FEB86659FD93)


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * _Q
    return x ^ (x >> np.uint64(29))


def shingle_set(text: str | None, width: int = WORDS) -> np.ndarray:
    """Sorted distinct 64-bit shingle hashes of a whole text; A-Z count as a-z.

    Fewer words than ``width`` make one shingle of the whole sequence; no words make none.
    """
    words = text.encode("utf-8", "surrogatepass").lower().split() if text else []
    n = len(words)
    if not n:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(xxh3_64_intdigest, words), np.uint64, n)
    m = min(n, width)
    s = h[: n - m + 1].copy()
    for i in range(1, m):
        s = s * _P + h[i : n - m + 1 + i]
    s += np.uint64(m)
    return np.unique(mixed(s))


def multipliers(k: int) -> tuple[np.ndarray, np.ndarray]:
    draw = np.random.default_rng(20_24)
    a = draw.integers(0, 2**63, k, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    return a, draw.integers(0, 2**63, k, dtype=np.uint64)


def signature(shingles: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """16 bits of each of len(a) min-hashes."""
    least = np.full(len(a), np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(shingles), 2048):
        part = shingles[at : at + 2048, None] * a[None, :]
        part += b[None, :]
        part ^= part >> np.uint64(31)
        np.minimum(least, part.min(axis=0), out=least)
    return (mixed(least) >> np.uint64(48)).astype(">u2")


def shared(a: np.ndarray, b: np.ndarray) -> int:
    """Size of the intersection of two sorted distinct arrays."""
    both = np.concatenate((a, b))
    both.sort(kind="stable")
    return int((both[1:] == both[:-1]).sum())
