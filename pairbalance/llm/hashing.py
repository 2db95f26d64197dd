"""64-bit hashing of words in Python workers."""

from __future__ import annotations

import numpy as np
import xxhash

from .common import Bounded

GOLDEN = np.uint64(0x9E3779B97F4A7C15)
CACHED_BYTES = 16 << 20


def mix(x: np.ndarray) -> np.ndarray:
    """Scramble unsigned 64-bit integers, one to one."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


class WordHashes:
    """Hashes of words, cached."""

    def __init__(self, most: int = CACHED_BYTES):
        self.known = Bounded(lambda w: xxhash.xxh3_64_intdigest(w), most)

    def __call__(self, words: list[str]) -> np.ndarray:
        return np.fromiter(map(self.known.__getitem__, words), np.uint64, len(words))


def runs(values: np.ndarray, n: int) -> np.ndarray:
    """A hash of each n neighbouring values."""
    if len(values) < n:
        return values[:0]
    with np.errstate(over="ignore"):
        out = values[: len(values) - n + 1].copy()
        for i in range(1, n):
            out = out * GOLDEN + values[i : len(values) - n + 1 + i]
    return mix(out)
