"""Bit vectors with rank: 64-bit words and the ones before each word."""

from __future__ import annotations

import numpy as np


class Bits:
    def __init__(self, bits: np.ndarray):
        self.n = len(bits)
        padded = np.zeros(-(-max(1, self.n) // 64) * 64, np.uint8)
        padded[: self.n] = bits
        self.words = np.packbits(padded, bitorder="little").view("<u8")
        self.before = np.concatenate([[0], np.cumsum(np.bitwise_count(self.words))]).astype(np.int64)

    def rank1(self, i):
        """Ones among the first i bits; i may be an array."""
        i = np.asarray(i)
        w, r = i >> 6, (i & 63).astype(np.uint64)
        word = self.words[np.minimum(w, len(self.words) - 1)]
        low = np.where(r > 0, word & ((np.uint64(1) << r) - np.uint64(1)), 0)
        return self.before[w] + np.bitwise_count(low).astype(np.int64) * (w < len(self.words))

    def rank0(self, i):
        return np.asarray(i) - self.rank1(i)

    def __getitem__(self, i: int) -> int:
        return int(self.words[i >> 6] >> np.uint64(i & 63)) & 1

    def nbytes(self) -> int:
        return self.words.nbytes + self.before.nbytes
