"""Space-filling curves: Morton by bit expressions, Hilbert in NumPy; nearby cells get nearby numbers."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def quantise(c: Column, lo: float, hi: float, bits: int) -> Column:
    top = (1 << bits) - 1
    return F.least(F.greatest(F.floor((c - float(lo)) / (float(hi - lo) or 1.0) * (1 << bits)), F.lit(0)), F.lit(top)).cast("long")


def morton(ints: list[Column], bits: int) -> Column:
    """Interleaved bits, the first coordinate's highest."""
    out, d = F.lit(0).cast("long"), len(ints)
    for b in range(bits):
        for k, c in enumerate(ints):
            out = out + F.shiftleft(F.shiftright(c, b).bitwiseAND(F.lit(1)), b * d + (d - 1 - k))
    return out


def morton_sql(ints: list[str], bits: int) -> str:
    d = len(ints)
    return " + ".join(f"((({c}) >> {b}) & 1) * {1 << (b * d + d - 1 - k)}" for b in range(bits) for k, c in enumerate(ints))


def morton_numbers(q: np.ndarray, bits: int) -> np.ndarray:
    out = np.zeros(len(q), np.int64)
    d = q.shape[1]
    for b in range(bits):
        for k in range(d):
            out |= ((q[:, k] >> b) & 1) << (b * d + d - 1 - k)
    return out


def hilbert_numbers(q: np.ndarray, bits: int) -> np.ndarray:
    """Hilbert index of integer points [n, d]: axes are transposed by undoing rotations, then bits interleaved."""
    x = q.astype(np.int64).T.copy()
    d = len(x)
    top = 1 << (bits - 1)
    level = top
    while level > 1:
        low = level - 1
        for k in range(d):
            on = (x[k] & level) > 0
            swap = np.where(on, 0, (x[0] ^ x[k]) & low)
            x[0] = np.where(on, x[0] ^ low, x[0] ^ swap)
            x[k] = x[k] ^ swap
        level >>= 1
    for k in range(1, d):
        x[k] ^= x[k - 1]
    flip = np.zeros_like(x[0])
    level = top
    while level > 1:
        flip = np.where((x[d - 1] & level) > 0, flip ^ (level - 1), flip)
        level >>= 1
    return morton_numbers((x ^ flip).T, bits)


def curve_order(points: np.ndarray, kind: str = "morton", bits: int = 8) -> np.ndarray:
    """Curve numbers of points over their own bounding box."""
    lo, hi = points.min(0), points.max(0)
    q = np.clip(np.floor((points - lo) / np.where(hi > lo, hi - lo, 1) * (1 << bits)), 0, (1 << bits) - 1).astype(np.int64)
    return morton_numbers(q, bits) if kind == "morton" else hilbert_numbers(q, bits)
