"""Word shingles as sorted arrays of 64-bit numbers.

Equal shingles are taken as equal numbers: within one pair of sets two different
shingles of a few thousand share a number with a chance below 1e-11.
"""

from __future__ import annotations

import numpy as np
import xxhash

from vpatterns.llm.common import ASCII_LOWER

#: Words whose numbers are at hand; more would not stay in the processor's cache.
CACHE = 50_000
_M1, _M2, _M3 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB), np.uint64(0x9E3779B97F4A7C15)


class WordIds(dict):
    """A number for each word; it starts anew when full, numbers stay the same."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= CACHE:
            self.clear()
        got = self[word] = xxhash.xxh3_64_intdigest(word)
        return got


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _M1
    x = (x ^ (x >> np.uint64(27))) * _M2
    return x ^ (x >> np.uint64(31))


def shingle_set(text: str | None, ids: WordIds, width: int = 5) -> np.ndarray:
    """Sorted distinct shingles; fewer words are one shingle, none are no shingle."""
    words = (text or "").encode("utf-8", "surrogatepass").translate(ASCII_LOWER).split()
    if not words:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(ids.__getitem__, words), np.uint64, len(words))
    n = len(words) - width + 1
    if n < 1:
        number = np.array([len(words)], np.uint64)  # a whole short text is no window of a longer one
        for x in h:
            number = mixed(number * _M3 + x)
        return number
    out = h[:n].copy()
    for i in range(1, width):
        out = out * _M3 + h[i : i + n]
    return np.unique(mixed(out))
