"""Words, shingles and their 64-bit hashes, block-wise in numpy."""

from __future__ import annotations

import numpy as np
import xxhash

#: A worker forgets its words when it knows this many.
_KNOWN = 1 << 16
_STEP = np.uint64(0x9E3779B97F4A7C15)


class _WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= _KNOWN:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value


_hashes = _WordHashes()


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(_hashes.__getitem__, words), np.uint64, len(words))


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers that spreads every bit (the splitmix finaliser)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def window_hashes(words: np.ndarray, size: int) -> np.ndarray:
    """A hash of each run of ``size`` words; empty if there are fewer."""
    n = len(words) - size + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    total = words[:n].copy()
    for k in range(1, size):
        total *= _STEP
        total += words[k : k + n]
    return mixed(total)


def shingle_set(words: list[bytes], size: int) -> np.ndarray:
    """Sorted distinct shingles; a shorter text is one shingle, a text without words none."""
    if not words:
        return np.empty(0, np.uint64)
    hashed = word_hashes(words)
    return np.unique(window_hashes(hashed, min(size, len(words))))
