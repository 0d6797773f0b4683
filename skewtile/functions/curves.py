"""Morton and Hilbert codes of grid cells."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

# The masks that spread 16 bits to every second place, and their shifts.
_SPREAD = ((8, 0x00FF00FF), (4, 0x0F0F0F0F), (2, 0x33333333), (1, 0x55555555))


def spread_column(v: Column) -> Column:
    v = v.cast("long")
    for shift, mask in _SPREAD:
        v = v.bitwiseOR(F.shiftleft(v, shift)).bitwiseAND(F.lit(mask).cast("long"))
    return v


def morton_column(gx: Column, gy: Column) -> Column:
    """The Z-order code of cell (gx, gy), both below 65,536."""
    return spread_column(gx).bitwiseOR(F.shiftleft(spread_column(gy), 1))


def morton(gx: np.ndarray, gy: np.ndarray) -> np.ndarray:
    def spread(v: np.ndarray) -> np.ndarray:
        v = v.astype(np.int64)
        for shift, mask in _SPREAD:
            v = (v | (v << shift)) & mask
        return v

    return spread(gx) | (spread(gy) << 1)


def unmorton(code: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    def gather(v: np.ndarray) -> np.ndarray:
        out = np.zeros_like(v)
        for bit in range(16):
            out |= ((v >> (2 * bit)) & 1) << bit
        return out

    return gather(code), gather(code >> 1)


def hilbert(gx: np.ndarray, gy: np.ndarray, order: int = 16) -> np.ndarray:
    """The Hilbert index of cells of a 2^order grid, by turning each quadrant into the first one's frame."""
    x, y = gx.astype(np.int64).copy(), gy.astype(np.int64).copy()
    out = np.zeros_like(x)
    for k in reversed(range(order)):
        side = 1 << k
        rx, ry = (x & side) > 0, (y & side) > 0
        out += side * side * np.where(rx, np.where(ry, 2, 3), np.where(ry, 1, 0))
        x, y = x & (side - 1), y & (side - 1)
        flip = rx & ~ry
        x, y = np.where(flip, side - 1 - x, x), np.where(flip, side - 1 - y, y)
        x, y = np.where(ry, x, y), np.where(ry, y, x)
    return out


def to_grid(v: np.ndarray, low: float, high: float, cells: int) -> np.ndarray:
    """Cell numbers of values of [low, high]; the upper end belongs to the last cell."""
    if high <= low:
        return np.where(v > high, cells - 1, 0).astype(np.int64)
    return np.clip(np.floor((v - low) / (high - low) * cells), 0, cells - 1).astype(np.int64)
