"""Word spans and 64-bit hashes of words and word windows, vectorised over the UTF-8 bytes of many texts."""

from __future__ import annotations

import functools
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa

CHUNK_BYTES = 500_000
_ODD = np.uint64(0x9E3779B97F4A7C15)
_ODD2 = np.uint64(0xC2B2AE3D27D4EB4F)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers that spreads every input bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


@functools.cache
def _byte_values() -> np.ndarray:
    return mix(np.arange(1, 257, dtype=np.uint64) * _ODD2)


_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def powers(base: np.uint64, n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and its inverse modulo 2**64, for i below n."""
    held = _powers.get(int(base))
    if held is None or len(held[0]) < n:
        size = 1 << max(10, (n - 1).bit_length())
        inverse = np.uint64(pow(int(base), -1, 1 << 64))
        one = np.ones(1, np.uint64)
        held = _powers[int(base)] = tuple(np.concatenate([one, np.cumprod(np.full(size - 1, b, np.uint64), dtype=np.uint64)]) for b in (base, inverse))
    return held


def lower_table() -> np.ndarray:
    out = np.arange(256, dtype=np.uint8)
    out[65:91] += 32
    return out


LOWER = lower_table()


class Words(NamedTuple):
    data: np.ndarray  # lower-cased bytes of the chunk
    starts: np.ndarray  # of words, in the chunk's bytes
    ends: np.ndarray
    hashes: np.ndarray
    first: np.ndarray  # per document: the ordinal of its first word, and one more at the end


def texts(column: pa.Array | pa.ChunkedArray) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, bytes, byte offsets) of runs of whole texts, about CHUNK_BYTES each; null is empty."""
    column = column.cast(pa.large_string()).fill_null("")
    n = len(column)
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int64, n + 1, 8 * column.offset)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.empty(0, np.uint8)
    at = 0
    while at < n:
        end = max(at + 1, int(np.searchsorted(offsets, offsets[at] + CHUNK_BYTES, "right")) - 1)
        end = min(end, n)
        yield at, raw[offsets[at] : offsets[end]], offsets[at : end + 1] - offsets[at]
        at = end


def split_words(raw: np.ndarray, offsets: np.ndarray, is_word: np.ndarray) -> Words:
    """Maximal runs of word bytes within each text, hashed after lower-casing A-Z."""
    data = LOWER[raw]
    inside = is_word[data]
    n = len(data)
    docs = len(offsets) - 1
    if n == 0:
        none = np.empty(0, np.int64)
        return Words(data, none, none, np.empty(0, np.uint64), np.zeros(docs + 1, np.int64))
    before = np.empty(n, bool)
    before[0], before[1:] = False, inside[:-1]
    after = np.empty(n, bool)
    after[-1], after[:-1] = False, inside[1:]
    real = offsets[:-1][offsets[:-1] < offsets[1:]]
    before[real] = False
    after[offsets[1:][offsets[:-1] < offsets[1:]] - 1] = False
    starts, ends = np.flatnonzero(inside & ~before), np.flatnonzero(inside & ~after) + 1
    up, down = powers(_ODD, n + 1)
    sums = np.empty(n + 1, np.uint64)
    sums[0] = 0
    np.cumsum(_byte_values()[data] * up[:n], out=sums[1:])
    hashes = mix((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64))
    return Words(data, starts, ends, hashes, np.searchsorted(starts, offsets))


def window_hashes(hashes: np.ndarray, size: int) -> np.ndarray:
    """Hash of every ``size`` consecutive words, by the ordinal of its first; borders of texts are the caller's concern."""
    n = len(hashes)
    if n < size:
        return np.empty(0, np.uint64)
    up, down = powers(_ODD2, n + 1)
    sums = np.empty(n + 1, np.uint64)
    sums[0] = 0
    np.cumsum(hashes * up[:n], out=sums[1:])
    return mix((sums[size:] - sums[:-size]) * down[: n - size + 1] + np.uint64(size))
