"""Word shingles of whole texts as 64-bit hashes, in numpy."""

from __future__ import annotations

import numpy as np

_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))
_SPACE = np.zeros(256, bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def mix(x: np.ndarray) -> np.ndarray:
    """Spreads the bits of 64-bit numbers (the finaliser of a splittable generator)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def powers(n: int, base: np.uint64) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    if n:
        out[0] = 1
    return np.multiply.accumulate(out)


def word_hashes(text: str) -> np.ndarray:
    """A hash for every word (parts between ASCII white space, A-Z lowered), in order."""
    data = _LOWER[np.frombuffer(text.encode(), np.uint8)]
    if not len(data):
        return np.zeros(0, np.uint64)
    space = _SPACE[data]
    edge = np.diff(space.astype(np.int8), prepend=np.int8(1), append=np.int8(1))
    starts, ends = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
    if not len(starts):
        return np.zeros(0, np.uint64)
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * powers(len(data), _BASE), out=sums[1:])
    return mix((sums[ends] - sums[starts]) * powers(len(data), _INVERSE)[starts] + (ends - starts).astype(np.uint64))


def shingles(text: str, n: int = 5) -> np.ndarray:
    """Hashes of all runs of ``n`` words; a shorter text with words is one shingle."""
    words = word_hashes(text)
    if not len(words):
        return words
    n = min(n, len(words))
    total = np.zeros(len(words) - n + 1, np.uint64)
    for j in range(n):
        total = mix(total + words[j : j + len(total)] + np.uint64(j + 1))
    return total


def weighted(text: str, n: int = 5, counts: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingles, ascending, with weights: 1, or how often each occurs."""
    found, times = np.unique(shingles(text, n), return_counts=True)
    return found, times.astype(float) if counts else np.ones(len(found))


def similarity(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Weighted Jaccard similarity; two empty sets are alike."""
    both, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    low = float(np.minimum(a[1][i], b[1][j]).sum())
    high = float(a[1].sum() + b[1].sum()) - low
    return low / high if high else 1.0
