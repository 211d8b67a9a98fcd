"""Sets of word shingles and their Jaccard similarity, exact on whole sets.

Texts with one set (all blank ones, for instance) have one set id; a text of at most as many words as a shingle has one shingle.
"""

from __future__ import annotations

import numpy as np

SEED = 42
WORDS = 5
#: Least similarity, as a fraction of whole numbers.
LIMIT = (4, 5)
#: Shingles that are hashed at a time.
SLAB = 1 << 16


def shingles(text: bytes | None, words: int = WORDS, seed: int = SEED) -> np.ndarray:
    """Sorted hashes of the distinct shingles, without case; none of a blank text."""
    from xxhash import xxh64_intdigest

    parts = (text or b"").lower().split()
    if not parts:
        return np.zeros(0, np.uint64)
    if len(parts) <= words:
        return np.array([xxh64_intdigest(b" ".join(parts), seed)], np.uint64)
    n, found = len(parts) - words + 1, []
    for at in range(0, n, SLAB):
        piece = parts[at : min(n, at + SLAB) + words - 1]
        joined = map(b" ".join, zip(*(piece[i:] for i in range(words)), strict=False))
        found.append(np.unique(np.fromiter((xxh64_intdigest(s, seed) for s in joined), np.uint64, len(piece) - words + 1)))
    return found[0] if len(found) == 1 else np.unique(np.concatenate(found))


def similar(a: np.ndarray, b: np.ndarray, limit: tuple[int, int] = LIMIT) -> bool:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both * limit[1] >= (len(a) + len(b) - both) * limit[0]
