"""Token ids as Simple-8b words: 4 selector bits and 60 payload bits each.

A selector fixes how many ids of which width share a word.  A field of all ones is an
escape: the id itself stands in the segment's escape list.  An index holds, for every
block of 256 words, the ordinals of its first id and first escape, so that any block
decodes by itself and all words of one selector decode in one vector operation.

``write_tokens`` packs documents in ascending ``doc_id`` order into segments (whole
documents, about 64 Ki ids each), one Parquet row a segment, so that Spark's committer
publishes the files in any store it can write; ``read_tokens`` decodes them again.
Null text is empty text.  Null ids come first; rows with equal ids are ordered by a
hash of their text, then the text.  An empty table gives an empty table.
"""

from __future__ import annotations

import functools
import struct
import sys
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tolerant_gd.llm.store import materialise, modest_batches, shuffle_width
from tolerant_gd.llm.wordbpe import PieceCache, WordBpe

#: Ids per word; the field width is 60 // count.
COUNTS = (60, 30, 20, 15, 12, 10, 8, 7, 6, 5, 4, 3, 2, 1)
WIDTHS = tuple(60 // n for n in COUNTS)
BLOCK_WORDS = 256
SEGMENT_IDS = 65_536
MAGIC = b"S8BSEG01"
_HEAD = struct.Struct("<8sQQQQQ")


def _bits(ids: np.ndarray) -> np.ndarray:
    """Field width each id needs: all ones in a field is reserved, so id + 1 must fit."""
    return np.ceil(np.log2(ids.astype(np.float64) + 2)).astype(np.uint8)


def _escape_width(bits: np.ndarray) -> int:
    """The width from which ids are cheaper in the escape list than in their own field."""
    held = np.bincount(bits, minlength=64)
    slots = np.array([next((w for w in WIDTHS if w >= b), 60) for b in range(64)])
    costs = {w: (held[: w + 1] * slots[: w + 1]).sum() + held[w + 1 :].sum() * (slots[w] + 64) for w in WIDTHS if w >= 4}
    return min(costs, key=costs.get)


def pack(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(words, escapes, block index) of unsigned ids; the index has (first id, first escape) per block."""
    ids = ids.astype(np.uint64)
    n = len(ids)
    if n == 0:
        return np.empty(0, np.uint64), np.empty(0, np.uint64), np.empty((0, 2), np.uint64)
    bits = _bits(ids)
    cap = _escape_width(bits)
    escaped = bits > cap
    bits = np.where(escaped, 1, bits)  # an escape fits any field
    step = np.ones(n, np.int64)
    # widest group first overwritten by denser ones: the densest fitting selector wins
    for count, width in sorted(zip(COUNTS, WIDTHS, strict=True)):
        if count == 1:
            continue
        ok = np.concatenate([(bits <= width), np.ones(count, bool)])  # past the end anything fits
        run, have = ok, 1
        while have < count:
            shift = min(have, count - have)
            run = run[:-shift] & run[shift:]
            have += shift
        fits = run[:n]
        step[fits] = count
    jumps, starts, at = step.tolist(), [], 0
    while at < n:
        starts.append(at)
        at += jumps[at]
    starts = np.array(starts, np.int64)
    words = np.zeros(len(starts), np.uint64)
    counts = step[starts]
    padded = np.concatenate([np.where(escaped, 0, ids), np.zeros(60, np.uint64)])
    flags = np.concatenate([escaped, np.zeros(60, bool)])
    for selector, (count, width) in enumerate(zip(COUNTS, WIDTHS, strict=True)):
        chosen = np.flatnonzero(counts == count)
        if not len(chosen):
            continue
        at = starts[chosen][:, None] + np.arange(count)
        fields = np.where(flags[at], np.uint64((1 << width) - 1), padded[at])
        shifts = (np.arange(count) * width).astype(np.uint64)
        words[chosen] = np.bitwise_or.reduce(fields << shifts, axis=1) | np.uint64(selector << 60)
    firsts = starts[::BLOCK_WORDS]
    before = np.concatenate([[0], np.cumsum(escaped)])[firsts]
    return words, ids[escaped], np.stack([firsts, before], axis=1).astype(np.uint64)


def unpack(words: np.ndarray, escapes: np.ndarray, n: int) -> np.ndarray:
    """The first ``n`` ids of a run of words that starts at a block boundary."""
    if n == 0:
        return np.empty(0, np.uint64)
    selectors = (words >> np.uint64(60)).astype(np.int64)
    counts = np.array(COUNTS + (0, 0), np.int64)[selectors]
    starts = np.concatenate([[0], np.cumsum(counts)[:-1]])
    out = np.zeros(int(counts.sum()), np.uint64)
    marked = np.zeros(len(out), bool)
    for selector, (count, width) in enumerate(zip(COUNTS, WIDTHS, strict=True)):
        chosen = np.flatnonzero(selectors == selector)
        if not len(chosen):
            continue
        ones = np.uint64((1 << width) - 1)
        shifts = (np.arange(count) * width).astype(np.uint64)
        fields = (words[chosen][:, None] >> shifts) & ones
        at = starts[chosen][:, None] + np.arange(count)
        out[at] = fields
        marked[at] = fields == ones
    out, marked = out[:n], marked[:n]
    out[marked] = escapes[: int(marked.sum())]
    return out


def encode_segment(ids: np.ndarray, lengths: np.ndarray) -> bytes:
    words, escapes, index = pack(ids)
    head = _HEAD.pack(MAGIC, len(ids), len(lengths), len(words), len(escapes), len(index))
    return b"".join([head, lengths.astype("<u4").tobytes(), index.astype("<u8").tobytes(), escapes.astype("<u8").tobytes(), words.astype("<u8").tobytes()])


def _parts(blob: bytes):
    magic, n, docs, n_words, n_escapes, blocks = _HEAD.unpack_from(blob)
    if magic != MAGIC:
        raise ValueError("not a token segment")
    at = _HEAD.size
    lengths = np.frombuffer(blob, "<u4", docs, at)
    index = np.frombuffer(blob, "<u8", 2 * blocks, at := at + 4 * docs).reshape(-1, 2)
    escapes = np.frombuffer(blob, "<u8", n_escapes, at := at + 16 * blocks)
    words = np.frombuffer(blob, "<u8", n_words, at + 8 * n_escapes)
    return n, lengths, index, escapes, words


def decode_segment(blob: bytes) -> tuple[np.ndarray, np.ndarray]:
    """(ids, ids per document) of a whole segment."""
    n, lengths, _, escapes, words = _parts(blob)
    return unpack(words, escapes, n), lengths


def decode_block(blob: bytes, block: int) -> np.ndarray:
    """The ids of one block, by its offsets alone."""
    n, _, index, escapes, words = _parts(blob)
    end = int(index[block + 1, 0]) if block + 1 < len(index) else n
    return unpack(words[block * BLOCK_WORDS : (block + 1) * BLOCK_WORDS], escapes[int(index[block, 1]) :], end - int(index[block, 0]))


@functools.cache
def _library_ids(path: str):
    """text -> ids as little-endian u4 bytes, by the tokenizers library's model on cached pieces of text."""
    bpe = WordBpe(path)
    model = bpe.library.model
    if array("I").itemsize != 4 or sys.byteorder != "little":
        raise RuntimeError("packed ids are little-endian u4")

    def one(chunk: str) -> bytes:
        if two := bpe.stem_and_mark(chunk):
            return pieces[two[0]] + pieces[two[1]]
        found = bpe.words(chunk)
        if len(found) == 1:
            return array("I", [t.id for t in model.tokenize(bpe.symbols(found[0]))]).tobytes()
        return b"".join([words[w] for w in found])

    words = PieceCache(lambda w: array("I", [t.id for t in model.tokenize(bpe.symbols(w))]).tobytes(), 3_000_000)
    pieces = PieceCache(one, 180_000_000)
    added = {t: np.array([i], "<u4").tobytes() for t, i in bpe.added.items()}

    def encode(text: str) -> bytes:
        return b"".join([added[s] if special else b"".join(map(pieces.__getitem__, bpe.chunks(s))) for special, s in bpe.segments(text)])

    return encode


SEGMENT_SCHEMA = "part int, seq long, part_start long, n_ids long, doc_ids array<long>, blob binary"


def _packer(path: str, end_id: int | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = _library_ids(path)
        tail = b"" if end_id is None else np.array([end_id], "<u4").tobytes()
        part, seq, before = TaskContext.get().partitionId(), 0, 0
        ids, docs, held = [], [], 0

        def segment() -> pa.RecordBatch:
            flat = np.frombuffer(b"".join(ids), "<u4")
            lengths = np.array([len(x) // 4 for x in ids], np.uint32)
            columns = [pa.array([part], pa.int32()), pa.array([seq], pa.int64()), pa.array([before], pa.int64()), pa.array([held], pa.int64()), pa.array([docs], pa.list_(pa.int64())), pa.array([encode_segment(flat, lengths)], pa.binary())]
            return pa.RecordBatch.from_arrays(columns, ["part", "seq", "part_start", "n_ids", "doc_ids", "blob"])

        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                one = encode(text or "") + tail
                ids.append(one)
                docs.append(doc)
                held += len(one) // 4
                if held >= SEGMENT_IDS:
                    yield segment()
                    seq, before, ids, docs, held = seq + 1, before + held, [], [], 0
        if docs:
            yield segment()

    return run


def write_tokens(docs: DataFrame, tokenizer: str, end_id: int | None = 1) -> DataFrame:
    """Encode whole texts, write segments in ascending ``doc_id`` order, return the table of written segments."""
    modest_batches(docs.sparkSession)
    order = [F.col("doc_id").asc_nulls_first(), F.col("h"), F.col("text")]
    rows = docs.select(F.col("doc_id").cast("long"), "text", F.xxhash64("text").alias("h"))
    dealt = rows.repartitionByRange(shuffle_width(docs.sparkSession), *order[:2]).sortWithinPartitions(*order)
    return materialise(dealt.select("doc_id", "text").mapInArrow(_packer(tokenizer, end_id), SEGMENT_SCHEMA), "tokens")


def read_tokens(segments: DataFrame, crc: bool = True, with_ids: bool = False) -> DataFrame:
    """Per document: doc_id, start, n_tokens and, as asked, ids_crc32 and ids, decoded from the segments.

    The start adds two offsets: within the part file, kept by the writer, and of the parts before it,
    summed here over one row a part (as many as write tasks, whatever their size).
    """
    totals = segments.groupBy("part").agg(F.sum("n_ids").alias("ids"))
    bases = totals.select("part", (F.sum("ids").over(Window.orderBy("part")) - F.col("ids")).alias("base"))
    schema = "doc_id long, start long, n_tokens long" + ", ids_crc32 long" * crc + ", ids array<long>" * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                doc_ids, blob, start = (batch.column(i)[row] for i in range(3))
                ids, lengths = decode_segment(blob.as_py())
                ends = np.cumsum(lengths, dtype=np.int64)
                starts = ends - lengths
                columns = [doc_ids.values, pa.array(start.as_py() + starts), pa.array(lengths.astype(np.int64))]
                if crc:
                    raw = ids.astype("<u4").tobytes()
                    columns.append(pa.array([zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(starts, ends, strict=True)], pa.int64()))
                if with_ids:
                    columns.append(pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]), pa.int32()), pa.array(ids.astype(np.int64))))
                yield pa.RecordBatch.from_arrays(columns, [f.split()[0] for f in schema.split(", ")])

    placed = segments.join(F.broadcast(bases), "part")
    return placed.select("doc_ids", "blob", (F.col("base") + F.col("part_start")).alias("start")).mapInArrow(run, schema)
