"""Hashed word shingles of whole texts, computed batch-wise with numpy."""

from __future__ import annotations

import numpy as np
import xxhash

# Odd 64-bit multipliers of the polynomial over a window's words
# and of the finalising mixer.
_ODD = np.array(
    [
        0x9E3779B97F4A7C15,
        0xC2B2AE3D27D4EB4F,
        0x165667B19E3779F9,
        0xD6E8FEB86659FD93,
        0xFF51AFD7ED558CCD,
    ],
    dtype=np.uint64,
)
_MIX1 = np.uint64(0xBF58476D1CE4E5B9)
_MIX2 = np.uint64(0x94D049BB133111EB)
_CACHE_WORDS = 100_000


def mix64(x: np.ndarray) -> np.ndarray:
    """Bijective avalanche of unsigned 64-bit values."""
    x = x ^ (x >> np.uint64(30))
    x = x * _MIX1
    x = x ^ (x >> np.uint64(27))
    x = x * _MIX2
    return x ^ (x >> np.uint64(31))


class WordHasher(dict):
    """Word to 64-bit hash, remembered for frequent words up to a fixed number of entries."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= _CACHE_WORDS:
            self.clear()
        h = xxhash.xxh3_64_intdigest(word)
        if len(word) <= 48:
            self[word] = h
        return h


def split_words(text: bytes) -> list[bytes]:
    """Lower-cased (A-Z only) maximal stretches without space, tab, LF, VT, FF, CR."""
    return text.lower().split()


def shingle_set(words: list[bytes], hasher: WordHasher, width: int = 5) -> np.ndarray:
    """Sorted distinct hashes of all `width`-word windows; fewer words give one window; none gives none."""
    n = len(words)
    if n == 0:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(hasher.__getitem__, words), np.uint64, n)
    if n < width:
        acc = np.uint64(n)
        with np.errstate(over="ignore"):
            for j in range(n):
                acc = acc * _MIX2 + h[j] * _ODD[j % 5]
            return mix64(np.array([acc], np.uint64))
    m = n - width + 1
    acc = h[:m] * _ODD[0]
    for j in range(1, width):
        acc = acc + h[j : j + m] * (_ODD[j % 5] + np.uint64(2 * (j // 5)))
    return np.unique(mix64(acc))
