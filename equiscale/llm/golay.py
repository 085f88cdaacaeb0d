"""The perfect binary Golay code of length 23 as a fuzzy hash of short bit segments.

Every 23-bit word lies within 3 bits of exactly one codeword.  The keys of a word are the
indices of all codewords within 4 bits of it (1 or 6).  Two words that
differ in at most 2 bits have a word between them at distance at most 1 from either, so the codeword
nearest to that one is a key of both.
"""

from __future__ import annotations

from functools import lru_cache
from itertools import combinations

import numpy as np

# fixed value: generator polynomial of the code
GENERATOR = 0b110001110101


def _rest(x: int) -> int:
    for k in range(22, 10, -1):
        if x >> k & 1:
            x ^= GENERATOR << (k - 11)
    return x


@lru_cache(maxsize=1)
def _tables():
    unit = [_rest(1 << k) for k in range(23)]
    low, high = np.zeros(1 << 12, np.int64), np.zeros(1 << 11, np.int64)
    for table, shift, bits in ((low, 0, 12), (high, 12, 11)):
        for k in range(bits):
            table[np.arange(len(table)) >> k & 1 == 1] ^= unit[shift + k]
    patterns = [[] for _ in range(2048)]
    for weight in range(5):
        for at in combinations(range(23), weight):
            e, s = 0, 0
            for k in at:
                e |= 1 << k
                s ^= unit[k]
            patterns[s].append(e)
    near = np.full((2048, 6), -1, np.int64)
    for s, own in enumerate(patterns):
        near[s, : len(own)] = own
    return low, high, near


def indices(words: np.ndarray) -> np.ndarray:
    """For each 23-bit word six 12-bit codeword indices; -1 where there are fewer."""
    low, high, near = _tables()
    words = words.astype(np.int64)
    e = near[low[words & 0xFFF] ^ high[words >> 12]]
    return np.where(e < 0, -1, (words[:, None] ^ e) >> 11)
