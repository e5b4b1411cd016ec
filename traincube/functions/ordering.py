"""Space-filling orders: Morton keys as column expressions and as numpy, Hilbert keys as numpy."""

from __future__ import annotations

from math import floor, log2

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def unit(x: Column, low: Column | float, high: Column | float, bits: int) -> Column:
    """x rescaled to [0, 1); the upper edge is the last cell."""
    low, high = (F.lit(v) if isinstance(v, float) else v for v in (low, high))
    return F.least(F.when(high > low, (x - low) / (high - low)).otherwise(0.0), F.lit(1.0 - 2.0**-bits))


def quantize(x: Column, bits: int) -> Column:
    return F.floor(x * F.lit(float(1 << bits))).cast("long")


def morton(axes: list[Column], bits: int) -> Column:
    """Bits of all axes in turn, the first axis most significant; bits times axes is 63 at most."""
    q, key = len(axes), F.lit(0).cast("long")
    for b in range(bits):
        for a, x in enumerate(axes):
            key = key.bitwiseOR(F.shiftleft(F.shiftright(x, b).bitwiseAND(F.lit(1).cast("long")), q * b + q - 1 - a))
    return key


def bits_for_extent(extent: float) -> int:
    """Bits at which a cell is smaller than the smallest extent in the unit cube."""
    return floor(log2(1 / extent)) + 1


def unit_array(x: np.ndarray, low: list[float], high: list[float], bits: int) -> np.ndarray:
    """Cells [..., axis] of points in the box."""
    span = np.array([h - a if h > a else 1.0 for a, h in zip(low, high)])
    return np.floor(np.minimum((x - np.array(low)) / span, 1.0 - 2.0**-bits) * (1 << bits)).astype(np.int64)


def morton_array(cells: np.ndarray, bits: int) -> np.ndarray:
    q, key = cells.shape[-1], np.zeros(cells.shape[:-1], np.int64)
    for b in range(bits):
        for a in range(q):
            key |= ((cells[..., a] >> b) & 1) << (q * b + q - 1 - a)
    return key


def hilbert_array(cells: np.ndarray, bits: int) -> np.ndarray:
    """Keys along a Hilbert curve, by turning cells into its transposed form bit by bit."""
    x = [cells[..., a].copy() for a in range(cells.shape[-1])]
    q = len(x)
    for b in range(bits - 1, 0, -1):
        top, low = 1 << b, (1 << b) - 1
        for a in range(q):
            on = (x[a] & top) > 0
            swap = np.where(on, 0, (x[0] ^ x[a]) & low)
            x[0] = np.where(on, x[0] ^ low, x[0]) ^ swap
            x[a] = x[a] ^ swap
    for a in range(1, q):
        x[a] ^= x[a - 1]
    flip = np.zeros_like(x[0])
    for b in range(bits - 1, 0, -1):
        flip ^= np.where((x[-1] >> b) & 1, (1 << b) - 1, 0)
    return morton_array(np.stack([v ^ flip for v in x], -1), bits)
