"""Benchmark decontamination by a broadcast hash set of normalised word windows.

A word is a run of digits, a-z (A-Z lowered) and all characters from U+0080 on.  Windows
of the test items go to every executor as sorted 64-bit hashes with the words behind them;
windows of the documents are hashed in vector operations, looked up, and each hit is
verified against the words themselves, so a hash collision cannot count.

The broadcast is checked: test items are dealt into slices of at most ``slice_chars``
characters, each slice is scanned for by itself, and the hits are united per document, so
a benchmark of any size works and no broadcast grows with it.  Null text has no words; an
empty benchmark or table gives no hits or no rows; repeated rows each get their own row;
an item without words has no windows; items with equal windows are all reported; an item without
an id hits words like any other but is in no list or count of items.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tolerant_gd.llm.bytewords import split_words, texts, window_hashes
from tolerant_gd.llm.store import modest_batches

WINDOW = 10
SLICE_CHARS = 4_000_000


def word_bytes() -> np.ndarray:
    out = np.zeros(256, bool)
    out[48:58] = out[97:123] = out[128:] = True
    return out


IS_WORD = word_bytes()


_NONE = np.empty(0, np.int64)


class WindowSet:
    """The windows of test items, by window length: sorted hashes, and where in the items' words each window stands.

    Some 40 bytes a word in all, in arrays: ``slices`` bounds the number of words.
    """

    def __init__(self, items: list[tuple[str | None, str]], size: int = WINDOW):
        self.names, words, firsts, found = [item for item, _ in items], [], [0], {}
        for number, (_, text) in enumerate(items):
            raw = np.frombuffer((text or "").encode("utf-8", "surrogatepass"), np.uint8)
            w = split_words(raw, np.array([0, len(raw)]), IS_WORD)
            k = min(size, len(w.starts))
            if k:
                hashes = window_hashes(w.hashes, k)
                found.setdefault(k, []).append((hashes, np.full(len(hashes), number), firsts[-1] + np.arange(len(hashes))))
            words.append((w.data, w.starts, w.ends))
            firsts.append(firsts[-1] + len(w.starts))
        sizes = np.cumsum([0] + [len(d) for d, _, _ in words])
        self.data = np.concatenate([d for d, _, _ in words]) if words else np.empty(0, np.uint8)
        self.starts = np.concatenate([s + at for (_, s, _), at in zip(words, sizes, strict=False)]) if words else _NONE
        self.ends = np.concatenate([e + at for (_, _, e), at in zip(words, sizes, strict=False)]) if words else _NONE
        self.by_size = {}
        for k, parts in found.items():
            hashes, number, at = (np.concatenate(x) for x in zip(*parts, strict=True))
            order = np.argsort(hashes, kind="stable")
            self.by_size[k] = (hashes[order], number[order], at[order])
        self.filters = {k: self._filter(h) for k, (h, _, _) in self.by_size.items()}

    @staticmethod
    def _filter(hashes: np.ndarray) -> np.ndarray:
        """A bit per hash prefix: most windows are refused by one look."""
        out = np.zeros(1 << 20, bool)
        out[(hashes >> np.uint64(44)).astype(np.int64)] = True
        return out

    def window(self, at: int, k: int) -> bytes:
        return b" ".join([self.data[a:b].tobytes() for a, b in zip(self.starts[at : at + k], self.ends[at : at + k], strict=True)])

    def scan(self, column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, set[str]]]:
        """(row, words, ordinals of hit words, items) of every row."""
        for row, raw, offsets in texts(column):
            w = split_words(raw, offsets, IS_WORD)
            counts = np.diff(w.first)
            hit = np.zeros(len(w.starts), bool)
            items: dict[int, set[str]] = {}
            for k, (known, number, place) in self.by_size.items():
                hashes = window_hashes(w.hashes, k)
                at = np.flatnonzero(self.filters[k][(hashes >> np.uint64(44)).astype(np.int64)])
                low, high = np.searchsorted(known, hashes[at], "left"), np.searchsorted(known, hashes[at], "right")
                docs = np.searchsorted(w.first, at, "right") - 1
                inside = (low < high) & (at + k <= w.first[docs + 1])
                for doc, p, a, b in zip(docs[inside].tolist(), at[inside].tolist(), low[inside].tolist(), high[inside].tolist(), strict=True):
                    words = b" ".join([w.data[x:y].tobytes() for x, y in zip(w.starts[p : p + k], w.ends[p : p + k], strict=True)])
                    seen: dict[int, bool] = {}  # an item may hold a window many times
                    for i in range(a, b):
                        if not seen.get(int(number[i])):
                            seen[int(number[i])] = self.window(int(place[i]), k) == words
                    true = [self.names[i] for i, same in seen.items() if same]
                    if true:
                        hit[p : p + k] = True
                        items.setdefault(doc, set()).update(x for x in true if x is not None)
            for doc, n in enumerate(counts.tolist()):
                own = items.get(doc)
                yield row + doc, n, _NONE if own is None else np.flatnonzero(hit[w.first[doc] : w.first[doc + 1]]), own or set()


def slices(benchmark: DataFrame, slice_chars: int = SLICE_CHARS, size: int = WINDOW) -> list[DataFrame]:
    """The test items in parts whose text is small enough to broadcast (the size is read, not assumed).

    An item longer than a slice is itself dealt in runs of words that overlap by a window less one word.
    """
    sized = benchmark.select(F.col("item_id").cast("string").alias("item"), "text").where("text is not null")
    longest, chars = sized.agg(F.max(F.length("text")), F.sum(F.length("text"))).first()
    n = -(-(chars or 0) // slice_chars)
    if n <= 1:
        return [sized]
    if longest > slice_chars:
        run = max(1, slice_chars // 16)
        words = F.regexp_extract_all("text", F.lit(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"), F.lit(0))
        cut = sized.select("item", "text", F.when(F.length("text") > slice_chars, words).alias("w"))
        starts = F.sequence(F.lit(1), F.greatest(F.size("w") - (size - 1), F.lit(1)), F.lit(run))
        runs = F.transform(starts, lambda at: F.array_join(F.slice("w", at, run + size - 1), " "))
        sized = cut.select("item", F.explode(F.when(F.col("w").isNull(), F.array("text")).otherwise(runs)).alias("text"))
    return [sized.where(F.pmod(F.xxhash64("item", "text"), F.lit(n)) == i) for i in range(n)]


def scan(docs: DataFrame, benchmark: DataFrame, size: int = WINDOW, slice_chars: int = SLICE_CHARS, keep: list[str] | None = None) -> DataFrame:
    """``keep`` columns (default doc_id) with n_words, hits (ordinals of hit words) and items (sorted ids)."""
    keep = keep or ["doc_id"]
    spark, parts = docs.sparkSession, slices(benchmark, slice_chars, size)
    modest_batches(spark)
    inside = keep == ["_whole"]  # a packed row holds the text already
    rows = docs.select(*(F.col(c) for c in keep), *([] if inside else [F.col("text").alias("_text")]))
    found = None
    if len(parts) > 1:
        rows = rows.withColumn("_row", F.xxhash64(*[F.col(c) for c in rows.columns]))
    names = [c for c in rows.columns if c != "_text"]
    names_at = len(names)
    kinds = {f.name: f.dataType.simpleString() for f in rows.schema}
    schema = ", ".join(f"`{c}` {kinds[c]}" for c in names) + ", n_words long, hits array<int>, items array<string>"
    for part in parts:
        held = spark.sparkContext.broadcast(WindowSet([tuple(r) for r in part.collect()], size))

        def run(batches: Iterator[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            windows = held.value
            for batch in batches:
                result = list(windows.scan(batch.column(0).field("text") if inside else batch.column(names_at)))
                out = [pa.array([r[1] for r in result], pa.int64()), pa.array([r[2] for r in result], pa.list_(pa.int32())), pa.array([sorted(r[3]) for r in result], pa.list_(pa.string()))]
                yield pa.RecordBatch.from_arrays([*batch.columns[: len(names)], *out], [*names, "n_words", "hits", "items"])
            pa.default_memory_pool().release_unused()

        one = rows.select(*names, *([] if inside else ["_text"])).mapInArrow(run, schema)
        found = one if found is None else found.unionByName(one)
    if len(parts) > 1:  # equal rows have equal results, so they may share a group; their number is kept
        many = found.groupBy(*names).agg(F.max("n_words").alias("n_words"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("hits")))).alias("hits"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"), (F.count("*") / len(parts)).cast("int").alias("_n"))
        found = many.withColumn("_n", F.explode(F.sequence(F.lit(1), "_n"))).drop("_n", "_row")
    return found


def report(docs: DataFrame, benchmark: DataFrame, size: int = WINDOW, slice_chars: int = SLICE_CHARS) -> DataFrame:
    """Per document: n_words, n_hit, n_items, items_sha256, contaminated."""
    found = scan(docs, benchmark, size, slice_chars)
    return found.select("doc_id", "n_words", F.size("hits").cast("long").alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", "items"), 256).alias("items_sha256"), (F.size("hits") > 0).alias("contaminated"))


def _packed(docs: DataFrame) -> DataFrame:
    """The whole row in one column, so that no name of ``docs`` can clash with ours."""
    return docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_whole"))


def remove_documents(docs: DataFrame, benchmark: DataFrame, max_share: float = 0.0, size: int = WINDOW) -> DataFrame:
    """Documents whose share of hit words is at most ``max_share``, all columns as they were."""
    found = scan(_packed(docs), benchmark, size, keep=["_whole"])
    return found.where(F.size("hits") <= F.col("n_words") * F.lit(max_share)).select("_whole.*")


def remove_spans(docs: DataFrame, benchmark: DataFrame, size: int = WINDOW) -> DataFrame:
    """All documents, with hit words and what stands between neighbouring ones cut out of the text."""
    found = scan(_packed(docs), benchmark, size, keep=["_whole"]).select("_whole.*", F.col("hits").alias("_hits"))
    names, at = docs.columns, docs.columns.index("text")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = [t if not h else _cut(t, h) for t, h in zip(batch.column(at).to_pylist(), batch.column(batch.num_columns - 1).to_pylist(), strict=True)]
            columns = [pa.array(out, pa.string()) if i == at else batch.column(i) for i in range(len(names))]
            yield pa.RecordBatch.from_arrays(columns, names)

    return found.mapInArrow(cut, docs.schema)


def _cut(text: str, hits: list[int]) -> str:
    raw = text.encode("utf-8", "surrogatepass")
    w = split_words(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]), IS_WORD)
    out, at, i = [], 0, 0
    while i < len(hits):
        j = i
        while j + 1 < len(hits) and hits[j + 1] == hits[j] + 1:
            j += 1
        out.append(raw[at : w.starts[hits[i]]])
        at, i = int(w.ends[hits[j]]), j + 1
    return b"".join([*out, raw[at:]]).decode("utf-8", "surrogatepass")
