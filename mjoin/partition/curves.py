"""Orders of the cells of a grid: Hilbert, Z-order and row-major, as vectorised numpy."""

from __future__ import annotations

import numpy as np


def cells(bits: tuple[int, ...]) -> np.ndarray:
    """Coordinates of all cells, one row each; the first dimension varies slowest."""
    grid = np.indices([1 << b for b in bits]).reshape(len(bits), -1).T
    return np.ascontiguousarray(grid.astype(np.int64))


def _interleave(x: np.ndarray, bits: int) -> np.ndarray:
    out = np.zeros(x.shape[0], np.int64)
    for level in range(bits - 1, -1, -1):
        for d in range(x.shape[1]):
            out = (out << 1) | ((x[:, d] >> level) & 1)
    return out


def hilbert_index(coords: np.ndarray, bits: int) -> np.ndarray:
    """Position on the Hilbert curve of each row of coordinates, by the published bit transform on transposed Gray codes."""
    x = np.array(coords, np.int64).T.copy()
    m = len(x)
    level = 1 << (bits - 1) if bits else 0
    while level > 1:
        low = level - 1
        for d in range(m):
            set_ = (x[d] & level) > 0
            swap = np.where(set_, 0, (x[0] ^ x[d]) & low)
            x[0] ^= np.where(set_, low, swap)
            x[d] ^= swap
        level >>= 1
    for d in range(1, m):
        x[d] ^= x[d - 1]
    turn = np.zeros(x.shape[1], np.int64)
    level = 1 << (bits - 1) if bits else 0
    while level > 1:
        turn ^= np.where(x[-1] & level, level - 1, 0)
        level >>= 1
    return _interleave((x ^ turn).T, bits)


def hilbert_coords(index: np.ndarray, m: int, bits: int) -> np.ndarray:
    """Coordinates of positions on the Hilbert curve: the inverse of hilbert_index."""
    grid = cells((bits,) * m)
    order = np.argsort(hilbert_index(grid, bits))
    return grid[order[np.asarray(index)]]


def zorder_index(coords: np.ndarray, bits: int) -> np.ndarray:
    return _interleave(np.asarray(coords, np.int64), bits)


def rowmajor_index(coords: np.ndarray, bits: int) -> np.ndarray:
    out = np.zeros(len(coords), np.int64)
    for d in range(np.shape(coords)[1]):
        out = (out << bits) | np.asarray(coords)[:, d]
    return out


CURVES = {"hilbert": hilbert_index, "zorder": zorder_index, "rowmajor": rowmajor_index}
