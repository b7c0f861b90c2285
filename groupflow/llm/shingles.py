"""Word shingles as sorted arrays of 64-bit hashes."""

from __future__ import annotations

import numpy as np
import xxhash

_MIX = np.uint64(0x9E3779B97F4A7C15)
_MUL = np.uint64(0xBF58476D1CE4E5B9)
_CACHE_LIMIT = 200_000


class _WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= _CACHE_LIMIT:
            self.clear()
        self[word] = value = xxhash.xxh64_intdigest(word)
        return value


_words = _WordHashes()


def words_of(text: str | None) -> list[bytes]:
    """Words of a text: A-Z lower-cased, split on space and \\x09-\\x0D only."""
    return text.encode("utf-8", "surrogatepass").lower().split() if text else []


def shingle_set(text: str | None, width: int = 5) -> np.ndarray:
    """Sorted distinct shingle hashes; a text of fewer words is one shingle, no words is empty."""
    words = words_of(text)
    n = len(words)
    if not n:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(_words.__getitem__, words), np.uint64, n)
    span = min(width, n)
    acc = h[: n - span + 1].copy()
    for k in range(1, span):
        acc *= _MIX
        acc += h[k : n - span + 1 + k]
    # the span is part of the hash, so that a short text never equals a full shingle
    acc ^= np.uint64(span * 0x1F123BB5)
    acc ^= acc >> np.uint64(29)
    acc *= _MUL
    acc ^= acc >> np.uint64(32)
    return np.unique(acc)
