"""The perfect binary Golay code (23, 12, 7) as a fuzzy hash of 23-bit words."""

from __future__ import annotations

from functools import lru_cache
from itertools import combinations

import numpy as np

#: Fixed value: generator polynomial x^11 + x^10 + x^6 + x^5 + x^4 + x^2 + 1.
GENERATOR = 0xC75
BITS, CHECKS = 23, 11


def _remainder(word: int) -> int:
    for top in range(BITS - 1, CHECKS - 1, -1):
        if word >> top & 1:
            word ^= GENERATOR << (top - CHECKS)
    return word


@lru_cache(maxsize=1)
def tables() -> tuple[list[np.ndarray], np.ndarray, np.ndarray, np.ndarray]:
    """Syndromes by byte, then by syndrome: the error of weight 3 at most, its weight, and the errors of weight 4."""
    by_byte = [np.array([_remainder(v << shift) if v << shift < 1 << BITS else 0 for v in range(256)], dtype=np.int64) for shift in (0, 8, 16)]
    one = [_remainder(1 << i) for i in range(BITS)]
    near, weight, far = np.zeros(1 << CHECKS, np.int64), np.zeros(1 << CHECKS, np.int64), [[] for _ in range(1 << CHECKS)]
    for n in range(1, 5):
        for at in combinations(range(BITS), n):
            s = e = 0
            for i in at:
                s, e = s ^ one[i], e | 1 << i
            if n < 4:
                near[s], weight[s] = e, n
            else:
                far[s].append(e)
    return by_byte, near, weight, np.array([(x + [-1] * 5)[:5] for x in far], dtype=np.int64)


def decode(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each 23-bit word: the index of its nearest codeword, and the indices of all others at distance 4, -1 padded.

    If two words differ in one bit at most, the nearest codeword of either is nearest to, or at distance 4 from, the
    other: only words at distance 3 from their codeword (six in seven) have others at distance 4, always five.
    """
    by_byte, near, weight, far = tables()
    words = words.astype(np.int64)
    s = by_byte[0][words & 255] ^ by_byte[1][words >> 8 & 255] ^ by_byte[2][words >> 16 & 255]
    others = np.where(far[s] >= 0, (words[:, None] ^ far[s]) >> CHECKS, -1)
    return (words ^ near[s]) >> CHECKS, np.where(weight[s][:, None] == 3, others, -1)
