"""Vector arithmetic modulo the prime 2**61 - 1 on 64-bit integers."""

from __future__ import annotations

import numpy as np

PRIME = (1 << 61) - 1
_P = np.uint64(PRIME)
_LOW31, _LOW30 = np.uint64((1 << 31) - 1), np.uint64((1 << 30) - 1)


def reduced(x: np.ndarray) -> np.ndarray:
    """Values below 2**64 to their remainders."""
    x = (x & _P) + (x >> np.uint64(61))
    return x - _P * (x >= _P)


def elements(x: np.ndarray) -> np.ndarray:
    """Signed integers as field elements."""
    return np.mod(np.asarray(x, np.int64), np.int64(PRIME)).astype(np.uint64)


def times(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Products of field elements by limbs of 31 bits; 2**61 counts as 1."""
    s = np.uint64(31)
    a1, a0, b1, b0 = a >> s, a & _LOW31, b >> s, b & _LOW31
    middle = a1 * b0 + a0 * b1
    return reduced(np.uint64(2) * (a1 * b1) + (middle >> np.uint64(30)) + ((middle & _LOW30) << s) + a0 * b0)


def total(x: np.ndarray, axis: int = 0) -> np.ndarray:
    """Sums of up to 2**30 field elements along an axis."""
    s = np.uint64(31)
    low = (x & _LOW31).sum(axis=axis, dtype=np.uint64)
    high = reduced((x >> s).sum(axis=axis, dtype=np.uint64))
    return reduced(times(high, np.broadcast_to(np.uint64(1 << 31), high.shape)) + reduced(low))
