"""Random numbers as functions of keys: reruns, retries and other partitionings change nothing.

``portable`` is built on md5, so other SQL engines can replay it; ``fast`` on xxhash64;
``numpy_uniform`` is the vector form for whole arrays of keys.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def _column(k) -> Column:
    return k if isinstance(k, Column) else F.lit(k)


def portable_int(*keys) -> Column:
    """52 random bits of the keys joined by ``|``."""
    text = F.concat_ws("|", *[_column(k).cast("string") for k in keys])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 13), 16, 10).cast("bigint")


def portable(*keys) -> Column:
    """Uniform in (0, 1)."""
    return (portable_int(*keys) + 0.5) / F.lit(float(1 << 52))


def portable_sql(*keys: str) -> str:
    """The same 52 bits in DuckDB."""
    return f"('0x' || substr(md5(concat_ws('|', {', '.join(keys)})), 1, 13))::BIGINT"


def fast(*keys) -> Column:
    """Uniform in (0, 1) by xxhash64."""
    return (F.shiftrightunsigned(F.xxhash64(*[_column(k) for k in keys]), 12) + 0.5) / F.lit(float(1 << 52))


def numpy_uniform(seed: int, *keys: np.ndarray) -> np.ndarray:
    """Uniform in (0, 1) for every combination of broadcast integer keys."""
    h = np.uint64(seed * 0x9E3779B97F4A7C15 & (1 << 64) - 1)
    for k in keys:
        h = (h ^ np.asarray(k).astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        h = h ^ (h >> np.uint64(29))
        h = h * np.uint64(0xBF58476D1CE4E5B9)
        h = h ^ (h >> np.uint64(32))
    return ((h >> np.uint64(12)).astype(np.float64) + 0.5) / float(1 << 52)
