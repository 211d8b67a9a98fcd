"""Rank over a bitmap: how many bits are set before a place. Two structures, of about 25% and 3% of the bitmap."""

from __future__ import annotations

import numpy as np


def to_words(bits: np.ndarray) -> np.ndarray:
    """Booleans as 64-bit words, least bit first, padded to whole groups of 32 words."""
    padded = np.zeros(-(-max(1, len(bits)) // 2048) * 2048, np.uint8)
    padded[: len(bits)] = bits
    return np.packbits(padded, bitorder="little").view(np.uint64)


class TwoLevelRank:
    """For each 512 bits one absolute count and, in a second number, seven counts of nine bits inside the group."""

    def __init__(self, words: np.ndarray):
        self.words = words
        ones = np.bitwise_count(words).astype(np.int64).reshape(-1, 8)
        inside = np.cumsum(ones, 1)
        self.absolute = np.r_[0, np.cumsum(inside[:, -1])[:-1]]
        self.relative = np.zeros(len(ones), np.int64)
        for j in range(7):
            self.relative |= inside[:, j] << (9 * j)

    @classmethod
    def of(cls, words: np.ndarray, numbers: np.ndarray) -> TwoLevelRank:
        """From a bitmap and the stored counts."""
        out = cls.__new__(cls)
        out.words, (out.absolute, out.relative) = words, np.ascontiguousarray(numbers.reshape(-1, 2).T)
        return out

    bits = property(lambda self: 128 * len(self.absolute))

    def rank(self, at: np.ndarray) -> np.ndarray:
        word = at >> 6
        group, j = word >> 3, word & 7
        before = np.where(j > 0, (self.relative[group] >> (9 * np.maximum(j - 1, 0))) & 511, 0)
        below = (np.uint64(1) << (at & 63).astype(np.uint64)) - np.uint64(1)
        return self.absolute[group] + before + np.bitwise_count(self.words[word] & below)

    def numbers(self) -> np.ndarray:
        """Absolute and relative counts, in turn."""
        return np.stack([self.absolute, self.relative], 1).ravel()


class SampledRank:
    """One count for each 2048 bits; up to 32 words are counted on the way. Smaller and slower."""

    def __init__(self, words: np.ndarray):
        self.words = words
        self.samples = np.r_[0, np.cumsum(np.bitwise_count(words).astype(np.int64).reshape(-1, 32).sum(1))[:-1]]

    @classmethod
    def of(cls, words: np.ndarray, numbers: np.ndarray) -> SampledRank:
        out = cls.__new__(cls)
        out.words, out.samples = words, numbers
        return out

    bits = property(lambda self: 64 * len(self.samples))

    def rank(self, at: np.ndarray) -> np.ndarray:
        word = at >> 6
        group = word >> 5
        out = self.samples[group].copy()
        for j in range(32):
            w = group * 32 + j
            out += np.where(w < word, np.bitwise_count(self.words[w]).astype(np.int64), 0)
        below = (np.uint64(1) << (at & 63).astype(np.uint64)) - np.uint64(1)
        return out + np.bitwise_count(self.words[word] & below)

    def numbers(self) -> np.ndarray:
        return self.samples


RANKS = {"two_level": TwoLevelRank, "sparse_samples": SampledRank}
