"""The perfect binary Golay code of 23 bits, for keys that survive bit errors."""

from __future__ import annotations

from itertools import combinations

import numpy as np

#: Fixed value: a generator polynomial of the code, x^11 + x^10 + x^6 + x^5 + x^4 + x^2 + 1.
GENERATOR = 0b110001110101
LENGTH, CHECK = 23, 11


def _remainders() -> np.ndarray:
    """x^i modulo the generator."""
    out, r = [], 1
    for _ in range(LENGTH):
        out.append(r)
        r <<= 1
        if r >> CHECK & 1:
            r ^= GENERATOR
    return np.array(out, np.uint32)


class Golay:
    """Indices of the codewords within four bits of a word: one if it lies within two of a codeword, else six.

    Every word lies within three bits of one codeword, its home, and two words one bit
    apart therefore share the home of either: it is at most four bits from the other.
    """

    def __init__(self):
        unit = _remainders()
        low, high = np.zeros(1 << 12, np.uint32), np.zeros(1 << 11, np.uint32)
        for i in range(12):
            low ^= np.where(np.arange(1 << 12) >> i & 1, unit[i], np.uint32(0)).astype(np.uint32)
        for i in range(11):
            high ^= np.where(np.arange(1 << 11) >> i & 1, unit[12 + i], np.uint32(0)).astype(np.uint32)
        self.low, self.high = low, high
        found: list[list[int]] = [[] for _ in range(1 << CHECK)]
        for weight in range(5):
            for bits in combinations(range(LENGTH), weight):
                found[int(np.bitwise_xor.reduce(unit[list(bits)])) if bits else 0].append(sum(1 << b for b in bits))
        self.count = np.array([len(f) for f in found], np.int64)
        self.errors = np.zeros((1 << CHECK, 6), np.uint32)
        for s, f in enumerate(found):
            self.errors[s, : len(f)] = f

    def syndrome(self, words: np.ndarray) -> np.ndarray:
        return self.low[words & 0xFFF] ^ self.high[words >> 12]

    def home(self, words: np.ndarray) -> np.ndarray:
        """12-bit index of the nearest codeword."""
        return (words ^ self.errors[self.syndrome(words), 0]) >> CHECK

    def near(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row of the word, codeword index) for all codewords within four bits."""
        s = self.syndrome(words)
        n = self.count[s]
        rows = np.repeat(np.arange(len(words)), n)
        place = np.arange(len(rows)) - np.repeat(np.cumsum(n) - n, n)
        return rows, (words[rows] ^ self.errors[s[rows], place]) >> CHECK
