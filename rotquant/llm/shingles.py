"""Hashed word shingles of whole texts.

Words are runs of bytes that are not ASCII white space, after lower-casing A-Z. A shingle
is the 64-bit hash of n words in order; a text with fewer words has its whole sequence as
one shingle, a text without words has none.
"""

from __future__ import annotations

import numpy as np
import xxhash

from .common import claim

CACHE_WORDS = 200_000
#: Fixed odd multipliers of the mixing steps (public constants of common 64-bit mixers).
_STEP = np.uint64(0x9E3779B97F4A7C15)
_MIX1 = np.uint64(0xBF58476D1CE4E5B9)
_MIX2 = np.uint64(0x94D049BB133111EB)


class WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        h = xxhash.xxh64_intdigest(word)
        if len(self) < CACHE_WORDS:
            self[word] = h
        return h


_words = WordHashes()


def working() -> None:
    claim("shingles", _words.clear)


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _MIX1
    x = (x ^ (x >> np.uint64(27))) * _MIX2
    return x ^ (x >> np.uint64(31))


def shingle_set(text: str | None, n: int) -> np.ndarray:
    """Sorted distinct shingles as signed 64-bit integers."""
    words = text.encode("utf-8", "surrogatepass").lower().split() if text else []
    if not words:
        return np.empty(0, dtype=np.int64)
    ids = np.fromiter(map(_words.__getitem__, words), dtype=np.uint64, count=len(words))
    n = min(n, len(ids))
    h = np.full(len(ids) - n + 1, n, dtype=np.uint64)
    for i in range(n):
        h = mixed(h * _STEP + ids[i : len(ids) - n + 1 + i])
    return np.unique(h.view(np.int64))
