"""Fuzzy keys of 23-bit words by the perfect binary Golay code (23, 12).

Each word lies within three bits of exactly one codeword. The keys of a word are the codewords that lie within three bits of
the word or of one of its neighbours at distance one: one key if the word is two bits or less from its codeword, six
if it is three away. Two words at most two bits apart have a common neighbour, or are neighbours, and so share a key.
"""

from __future__ import annotations

from functools import lru_cache
from itertools import combinations

import numpy as np

BITS, CHECK = 23, 11
#: Fixed value: the code's generator polynomial x^11 + x^9 + x^7 + x^6 + x^5 + x + 1.
GENERATOR = 0b101011100011
MOST_KEYS = 6


def _remainder(word: int) -> int:
    for bit in range(BITS - 1, CHECK - 1, -1):
        if word >> bit & 1:
            word ^= GENERATOR << (bit - CHECK)
    return word


@lru_cache(maxsize=1)
def tables() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Remainders of the upper 12 bits; error patterns (2048, 6) by remainder, the nearest first; how many of them."""
    high = np.array([_remainder(m << CHECK) for m in range(1 << (BITS - CHECK))], dtype=np.int32)
    single = [_remainder(1 << b) for b in range(BITS)]
    errors = np.zeros((1 << CHECK, MOST_KEYS), dtype=np.int32)
    count = np.zeros(1 << CHECK, dtype=np.int32)
    near = np.zeros(1 << CHECK, dtype=np.int32)
    for weight in range(5):
        for places in combinations(range(BITS), weight):
            s = e = 0
            for b in places:
                s ^= single[b]
                e |= 1 << b
            if weight < 4:
                near[s] = weight
            elif near[s] != 3:
                continue
            errors[s, count[s]] = e
            count[s] += 1
    return high, errors, count


def keys(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(rows, keys): for each 23-bit word its keys as 12-bit codeword indices, the row of the word beside each."""
    high, errors, count = tables()
    words = words.astype(np.int32)
    s = high[words >> CHECK] ^ (words & ((1 << CHECK) - 1))
    n = count[s]
    rows = np.repeat(np.arange(len(words)), n)
    nth = np.arange(len(rows)) - np.repeat(np.cumsum(n) - n, n)
    return rows, (words[rows] ^ errors[s[rows], nth]) >> CHECK
