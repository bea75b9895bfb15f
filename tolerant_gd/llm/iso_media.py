"""ISO base media files as a column: a writer of raw 8-bit frames, and a reader of nested boxes.

The payload is cut into 24 x 24 frames of 8-bit grey samples (576 bytes), stored as they
are, so what is read back is what was written.  The reader walks the boxes, decodes the
sample tables (times, chunks, sizes, offsets, sync samples) and gives codec, duration and
the byte ranges of key frames; it seeks over the media data and never decodes it.

Null text is empty text; every payload is padded with bytes 255 to a positive multiple of
576.  Equal texts give equal files: nothing of a file depends on its row or on time.  A
file that is no such container raises ``ValueError`` with the fault (``tracks``, ``payload``, ``feature``), or
is a row with that in its ``error`` column (``describe``); no table is made larger than the file allows.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from tolerant_gd.llm.store import materialise, modest_batches

SIDE = 24
FRAME = SIDE * SIDE
RATE = 25  # frames a second
CHUNK_FRAMES = 64
BATCH_BYTES = 16_000_000
MOST_DEPTH = 32  # of boxes in boxes

#: Boxes that hold boxes.
CONTAINERS = frozenset([b"moov", b"trak", b"mdia", b"minf", b"stbl", b"dinf", b"edts", b"udta", b"mvex", b"moof", b"traf"])


def _box(kind: bytes, *parts: bytes) -> bytes:
    body = b"".join(parts)
    return struct.pack(">I4s", 8 + len(body), kind) + body


def _full(kind: bytes, *parts: bytes, version: int = 0, flags: int = 0) -> bytes:
    return _box(kind, struct.pack(">I", version << 24 | flags), *parts)


_MATRIX = struct.pack(">9I", 0x10000, 0, 0, 0, 0x10000, 0, 0, 0, 0x40000000)
_FTYP = _box(b"ftyp", b"qt  ", struct.pack(">I", 0), b"qt  isom")


def _moov(frames: int, first_byte: int) -> bytes:
    chunks = -(-frames // CHUNK_FRAMES)
    offsets = [first_byte + i * CHUNK_FRAMES * FRAME for i in range(chunks)]
    wide = offsets[-1] >= 1 << 32
    entry = _box(b"raw ", bytes(6), struct.pack(">H", 1), bytes(16), struct.pack(">HHIIIH", SIDE, SIDE, 72 << 16, 72 << 16, 0, 1), bytes(32), struct.pack(">Hh", 40, -1))
    last = frames - (chunks - 1) * CHUNK_FRAMES
    runs = [(1, CHUNK_FRAMES, 1)] if chunks > 1 or last == CHUNK_FRAMES else []
    if last != CHUNK_FRAMES:
        runs.append((chunks, last, 1))
    table = _box(
        b"stbl",
        _full(b"stsd", struct.pack(">I", 1), entry),
        _full(b"stts", struct.pack(">III", 1, frames, 1)),
        _full(b"stsc", struct.pack(">I", len(runs)), *(struct.pack(">III", *r) for r in runs)),
        _full(b"stsz", struct.pack(">II", FRAME, frames)),
        _full(b"co64" if wide else b"stco", struct.pack(">I", chunks), struct.pack(f">{chunks}{'Q' if wide else 'I'}", *offsets)),
    )
    media = _box(
        b"mdia",
        _full(b"mdhd", struct.pack(">IIIIHH", 0, 0, RATE, frames, 0x55C4, 0)),
        _full(b"hdlr", struct.pack(">I4s", 0, b"vide"), bytes(12), b"\0"),
        _box(b"minf", _full(b"vmhd", bytes(8), flags=1), _box(b"dinf", _full(b"dref", struct.pack(">I", 1), _full(b"url ", flags=1))), table),
    )
    track = _box(b"trak", _full(b"tkhd", struct.pack(">IIIII", 0, 0, 1, 0, frames), bytes(16), _MATRIX, struct.pack(">II", SIDE << 16, SIDE << 16), flags=3), media)
    movie = _full(b"mvhd", struct.pack(">IIIIIH", 0, 0, RATE, frames, 0x10000, 0x100), bytes(10), _MATRIX, bytes(24), struct.pack(">I", 2))
    return _box(b"moov", movie, track)


def store(payload: bytes) -> bytes:
    """The container of a payload whose length is a positive multiple of 576."""
    frames, rest = divmod(len(payload), FRAME)
    if rest or not frames:
        raise ValueError("a payload is a positive number of whole frames")
    size = len(payload) + 8
    head = struct.pack(">I4sQ", 1, b"mdat", size + 8) if size >= 1 << 32 else struct.pack(">I4s", size, b"mdat")
    first = len(_FTYP) + len(head)
    return b"".join([_FTYP, head, payload, _moov(frames, first)])


def pad(text: str | None) -> tuple[bytes, int]:
    raw = (text or "").encode("utf-8", "surrogatepass")
    return raw + b"\xff" * (-len(raw) % FRAME if raw else FRAME), len(raw)


def walk(data: bytes, start: int = 0, end: int | None = None, depth: int = 0) -> Iterator[tuple[int, bytes, int, int]]:
    """(depth, kind, body start, body end) of every box, parents before children."""
    at, end = start, len(data) if end is None else end
    while at < end:
        if end - at < 8:
            raise ValueError(f"cut box header at {at}")
        size, kind = struct.unpack_from(">I4s", data, at)
        body = at + 8
        if size == 1 and end - at < 16:
            raise ValueError(f"cut box header at {at}")
        if size == 1:
            size, body = struct.unpack_from(">Q", data, at + 8)[0], at + 16
        elif size == 0:
            size = end - at
        if size < body - at or at + size > end:
            raise ValueError(f"box at {at} leaves its parent")
        yield depth, kind, body, at + size
        if kind in CONTAINERS:
            if depth >= MOST_DEPTH:
                raise ValueError("boxes are nested too deep")
            yield from walk(data, body, at + size, depth + 1)
        at += size


class Track(NamedTuple):
    codec: str
    handler: str
    width: int
    height: int
    timescale: int
    duration: int
    sizes: np.ndarray
    offsets: np.ndarray
    times: np.ndarray
    sync: np.ndarray  # ordinals of key frames

    def key_ranges(self) -> list[tuple[int, int]]:
        """Byte ranges of key frames, neighbouring ones joined."""
        if not len(self.sync):
            return []
        first, last = self.offsets[self.sync], (self.offsets + self.sizes)[self.sync]
        new = np.concatenate([[True], first[1:] != last[:-1]])
        return list(zip(first[new].tolist(), last[np.concatenate([new[1:], [True]])].tolist(), strict=True))


def _numbers(data: bytes, at: int, end: int, count: int, kind: str) -> np.ndarray:
    if at + count * np.dtype(kind).itemsize > end:
        raise ValueError(f"table at {at} leaves its box")
    return np.frombuffer(data, kind, count, at).astype(np.int64)


def tracks(data: bytes) -> list[Track]:
    """The tracks of a container; ``ValueError`` for anything that is broken, whatever its bytes claim."""
    try:
        return _tracks(data)
    except (struct.error, KeyError, IndexError, OverflowError) as e:
        raise ValueError(f"broken container: {e}") from e


def _tracks(data: bytes) -> list[Track]:
    out: list[dict] = []
    for _, kind, a, b in walk(data):
        if kind == b"trak":
            out.append({})
        if not out:
            continue
        t = out[-1]
        if kind == b"mdhd":
            wide = data[a] == 1
            t["time"] = struct.unpack_from(">IQ" if wide else ">II", data, a + (20 if wide else 12))
        elif kind == b"hdlr" and "handler" not in t:
            t["handler"] = data[a + 8 : a + 12].decode("latin-1")
        elif kind == b"stsd":
            t["codec"] = data[a + 12 : a + 16].decode("latin-1")
            t["shape"] = struct.unpack_from(">HH", data, a + 40) if t.get("handler") == "vide" else (0, 0)
        elif kind in (b"stts", b"stsc"):
            width = 2 if kind == b"stts" else 3
            n = struct.unpack_from(">I", data, a + 4)[0]
            t[kind] = _numbers(data, a + 8, b, n * width, ">u4").reshape(-1, width)
        elif kind == b"stsz":
            same, n = struct.unpack_from(">II", data, a + 4)
            if same and n * same > len(data):
                raise ValueError("samples exceed the file")
            t["sizes"] = np.full(n, same, np.int64) if same else _numbers(data, a + 12, b, n, ">u4")
        elif kind in (b"stco", b"co64"):
            n = struct.unpack_from(">I", data, a + 4)[0]
            t["chunks"] = _numbers(data, a + 8, b, n, ">u4" if kind == b"stco" else ">u8")
        elif kind == b"stss":
            n = struct.unpack_from(">I", data, a + 4)[0]
            t["sync"] = _numbers(data, a + 8, b, n, ">u4") - 1
    return [_track(t) for t in out if "codec" in t]


def _track(t: dict) -> Track:
    sizes, chunks, runs = t["sizes"], t["chunks"], t[b"stsc"]
    ends = np.append(runs[1:, 0], len(chunks) + 1)
    spans = ends - runs[:, 0]
    if (spans < 0).any() or spans.sum() != len(chunks) or (runs[:, 1] * spans).sum() != len(sizes) or t[b"stts"][:, 0].sum() != len(sizes):
        raise ValueError("sample tables disagree")
    per_chunk = np.repeat(runs[:, 1], spans)
    firsts = np.cumsum(per_chunk) - per_chunk
    before = np.cumsum(sizes) - sizes
    offsets = np.repeat(chunks, per_chunk) + before - np.repeat(before[firsts[per_chunk > 0]], per_chunk[per_chunk > 0])
    steps = np.repeat(t[b"stts"][:, 1], t[b"stts"][:, 0])
    timescale, duration = t["time"]
    sync = t.get("sync", np.arange(len(sizes)))
    if len(sync) and (sync.min() < 0 or sync.max() >= len(sizes)):
        raise ValueError("key frames that are no samples")
    return Track(t["codec"], t.get("handler", ""), *t["shape"], timescale, duration, sizes, offsets, np.cumsum(steps) - steps, sync)


def _first(data: bytes) -> Track:
    found = tracks(data)
    if not found:
        raise ValueError("no track")
    return found[0]


def payload(data: bytes) -> bytes:
    """The samples of the first track, in order."""
    t = _first(data)
    if not len(t.sizes):
        return b""
    ends = t.offsets + t.sizes
    if t.offsets.min() < 0 or ends.max() > len(data):
        raise ValueError("samples outside the file")
    new = np.concatenate([[True], t.offsets[1:] != ends[:-1]])
    stop = np.concatenate([new[1:], [True]])
    return b"".join([data[a:b] for a, b in zip(t.offsets[new].tolist(), ends[stop].tolist(), strict=True)])


def feature(data: bytes) -> str:
    t = _first(data)
    keys = t.key_ranges() or [(0, 0)]
    seconds = t.duration / max(1, t.timescale)
    ranges = hashlib.sha256(",".join(f"{a}-{b}" for a, b in keys).encode()).hexdigest()[:16]
    return f"codec={t.codec.strip()} size={t.width}x{t.height} seconds={seconds:.2f} frames={len(t.sizes)} keyframes={len(t.sync)} key_bytes={keys[0][0]}-{keys[-1][1]} key_ranges={len(keys)}:{ranges}"


def _sliced(rows: Iterator[tuple], names: list[str], kinds: list[pa.DataType], weigh) -> Iterator[pa.RecordBatch]:
    held, weight = [], 0
    for row in rows:
        held.append(row)
        weight += weigh(row)
        if weight > BATCH_BYTES:
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*held, strict=True), kinds, strict=True)], names)
            held, weight = [], 0
    if held:
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*held, strict=True), kinds, strict=True)], names)


def write_media(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, media: the containers, written and read back from the shared folder."""

    modest_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows():
            for batch in batches:
                for i in range(batch.num_rows):
                    data, n = pad(batch.column(1)[i].as_py())
                    yield batch.column(0)[i].as_py(), n, store(data)

        yield from _sliced(rows(), ["doc_id", "n_bytes", "media"], [pa.int64(), pa.int64(), pa.binary()], lambda r: len(r[2]))

    return materialise(docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(run, "doc_id long, n_bytes long, media binary"), "media")


def describe(media: DataFrame) -> DataFrame:
    """Sizes, digests and container features of stored media; of a null or broken one, null features and the fault in ``error``."""
    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, error string"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [f.split()[0] for f in schema.split(", ")]
        for batch in batches:
            rows = []
            for data in batch.column(2):
                data = data.as_py()
                if data is None:
                    rows.append((*[None] * 6, "no media"))
                    continue
                whole = (len(data), hashlib.sha256(data).hexdigest())
                try:
                    held, about = payload(data), feature(data)
                    rows.append((len(held), hashlib.sha256(held).hexdigest(), zlib.crc32(held[-32:]), *whole, about, None))
                except ValueError as e:
                    rows.append((None, None, None, *whole, None, str(e)))
            kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string()]
            columns = [pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *columns], names)

    return media.mapInArrow(run, schema)
