"""Word shingles as sets of 64-bit hashes, computed batch-wise in numpy.

Words are the runs of bytes between ASCII white space, A-Z lower-cased. A shingle's
hash combines its words' hashes linearly with odd multipliers and mixes the sum, so
a text's shingles come from five shifted additions. Two different shingles share a
hash with probability about 2**-64.
"""

from __future__ import annotations

import numpy as np
import xxhash

U64 = np.uint64
#: Odd 64-bit multipliers, one for each place in a shingle (from a fixed seed).
_STEP = np.random.default_rng(5).integers(0, 1 << 63, 64, dtype=np.uint64) * U64(2) + U64(1)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finalizer over 64-bit words (xor-shift and multiply)."""
    x = x ^ (x >> U64(32))
    x = x * U64(0xD6E8FEB86659FD93)
    x = x ^ (x >> U64(32))
    x = x * U64(0xD6E8FEB86659FD93)
    return x ^ (x >> U64(32))


class WordHashes:
    """64-bit hashes of words, remembered up to ``limit`` different ones."""

    def __init__(self, limit: int = 400_000):
        self.limit, self.memory = limit, {}

    def __call__(self, words: list[bytes]) -> np.ndarray:
        memory = self.memory
        if len(memory) > self.limit:
            memory = self.memory = {}
        for w in set(words).difference(memory):
            memory[w] = xxhash.xxh3_64_intdigest(w)
        return np.fromiter(map(memory.__getitem__, words), np.uint64, len(words))


def shingle_set(text: bytes | None, hashes: WordHashes, width: int = 5) -> np.ndarray:
    """The sorted distinct shingle hashes of a text: its ``width``-word shingles,
    the whole sequence if it has fewer words, nothing without words or text."""
    words = text.lower().split() if text else []
    if not words:
        return np.zeros(0, np.uint64)
    h = hashes(words)
    n = max(1, len(h) - width + 1)
    total = np.full(n, U64(min(len(h), width)))
    for i in range(min(len(h), width)):
        total += h[i : i + n] * _STEP[i]
    return np.unique(mix(total))


class MinHash:
    """``size`` minwise values (32 bits each) of a set of 64-bit hashes."""

    def __init__(self, size: int = 128, seed: int = 7):
        rng = np.random.default_rng(seed)
        self.size = size
        self.times = rng.integers(0, 1 << 63, size, dtype=np.uint64) * U64(2) + U64(1)
        self.plus = rng.integers(0, 1 << 63, size, dtype=np.uint64)

    def __call__(self, s: np.ndarray) -> np.ndarray:
        best = np.full(self.size, ~U64(0))
        for at in range(0, len(s), 2048):  # a long text in bounded memory
            x = s[at : at + 2048, None] * self.times + self.plus
            np.minimum(best, (x ^ (x >> U64(29))).min(axis=0), out=best)
        return (mix(best) >> U64(32)).astype("<u4")
