"""Compact form for sending: a bit for each cell and the values of occupied cells only."""

from __future__ import annotations

import numpy as np


def pack_sparse(cells: np.ndarray, occupied: np.ndarray) -> tuple[bytes, bytes]:
    return np.packbits(occupied, bitorder="little").tobytes(), cells[occupied].tobytes()


def unpack_sparse(bitmap: bytes, values: bytes, capacity: int, dtype) -> tuple[np.ndarray, np.ndarray]:
    occupied = np.unpackbits(np.frombuffer(bitmap, np.uint8), count=capacity, bitorder="little").astype(bool)
    cells = np.zeros(capacity, dtype)
    cells[occupied] = np.frombuffer(values, dtype)
    return cells, occupied


def packed_bits(capacity: int, n_keys: int, fp_bits: int) -> int:
    """Each key owns one cell, so as many cells are occupied as there are keys."""
    return capacity + fp_bits * n_keys
