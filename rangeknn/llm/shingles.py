"""Words of a text as 64-bit numbers, and numbers of runs of words."""

from __future__ import annotations

import numpy as np
import xxhash

_M = np.uint64(0x9E3779B97F4A7C15)
_S = np.uint64(29)


def mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return h ^ (h >> _S)


class _Numbers(dict):
    def __missing__(self, word: bytes) -> int:
        h = self[word] = xxhash.xxh3_64_intdigest(word)
        return h


class WordHasher:
    """Words are the runs between the ASCII characters space and 9 to 13."""

    def __init__(self, limit: int = 120_000) -> None:
        self.limit, self.memo = limit, _Numbers()

    def numbers(self, words: list[bytes]) -> np.ndarray:
        memo = self.memo
        if len(memo) > self.limit:
            for key in list(memo)[: self.limit // 2]:
                del memo[key]
        return np.fromiter(map(memo.__getitem__, words), np.uint64, len(words))


def grams(h: np.ndarray, k: int) -> np.ndarray:
    """A number for each run of k words; none if there are fewer."""
    n = len(h) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.full(n, np.uint64(k))
    for i in range(k):
        out = out * _M + h[i : i + n]
    return mix(out)
