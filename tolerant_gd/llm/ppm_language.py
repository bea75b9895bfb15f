"""Language identification by prediction by partial matching.

Each language has a tree of byte contexts of varying length, counted on a bounded sample
of labelled documents and then frozen.  A byte costs its exact code length: -log2 of its
probability in the longest known context, or of an escape (method C, with exclusion of
what longer contexts have offered) times its probability in the next shorter one, down to
equal chances of all bytes.  All trees are compiled into one automaton whose states are
the contexts and whose table holds, for every state and byte, the code length in every
language, so scoring is two table look-ups a byte, in vector steps over many stretches of
text at once.  The language of least total length wins; ties go to the first by name.

Text is read as UTF-8 with A-Z and the capitals of U+00C0-U+00DE lowered and all ASCII
but letters read as blanks.  Null text, or text without any letter, is ``und`` with score
0; every row gives a row; without labelled rows everything is ``und``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tolerant_gd.llm.bytewords import texts
from tolerant_gd.llm.store import modest_batches

ORDER = 4
LEAST_COUNT = 40
#: Bound of the training sample: documents per language, and characters of one (longer ones come last, and only their start is learned).
SAMPLE_DOCS, SAMPLE_CHARS = 250, 30_000
STRETCH = 256


def _fold_table() -> np.ndarray:
    out = np.arange(256, dtype=np.uint8)
    out[:128] = 32
    out[97:123] = np.arange(97, 123)
    out[65:91] = np.arange(97, 123)
    return out


_FOLD = _fold_table()


def fold(raw: np.ndarray) -> np.ndarray:
    out = _FOLD[raw]
    capital = np.flatnonzero((raw[1:] >= 0x80) & (raw[1:] <= 0x9E) & (raw[1:] != 0x97) & (raw[:-1] == 0xC3)) + 1
    out[capital] += 0x20
    return out


class Model:
    """Automaton of contexts with code lengths; ``names`` are the languages."""

    def __init__(self, samples: dict[str, list[bytes]], order: int = ORDER, least: int = LEAST_COUNT):
        self.names, self.order = sorted(samples), order
        counts = {name: self._counts(docs, order, least) for name, docs in samples.items()}
        contexts = {b""} | {c for t in counts.values() for c in t}
        for c in list(contexts):  # every prefix too, so that one byte more is one step
            contexts.update(c[:k] for k in range(len(c)))
        states = sorted(contexts, key=lambda c: (len(c), c))
        number = {c: i for i, c in enumerate(states)}
        seen = np.zeros(256, bool)
        for t in counts.values():
            seen |= t[b""] > 0
        used = np.flatnonzero(seen)
        self.symbol = np.full(256, len(used), np.int64)  # the last symbol stands for all bytes never seen
        self.symbol[used] = np.arange(len(used))
        width = len(used) + 1
        self.step = np.zeros((len(states), width), np.int32)
        self.bits = np.zeros((len(states), width, len(self.names)), np.float32)
        for i, c in enumerate(states):
            for s, byte in enumerate(used.tolist()):
                longer = (c + bytes([byte]))[-order:] if order else b""
                while longer not in number:
                    longer = longer[1:]
                self.step[i, s] = number[longer]
            for k, name in enumerate(self.names):
                cost = self._cost(counts[name], c)
                self.bits[i, :-1, k] = cost[used]
                self.bits[i, -1, k] = cost[~seen].max() if (~seen).any() else 0

    @staticmethod
    def _counts(docs: list[bytes], order: int, least: int) -> dict[bytes, np.ndarray]:
        """context -> counts of the next byte, for contexts seen ``least`` times or more."""
        out: dict[bytes, np.ndarray] = {b"": np.zeros(256, np.int64)}
        folded = [fold(np.frombuffer(d, np.uint8)) for d in docs]
        for k in range(order + 1):
            parts = []
            for d in folded:
                if len(d) > k:
                    code = np.zeros(len(d) - k, np.uint64)
                    for j in range(k + 1):
                        code = code * np.uint64(256) + d[j : len(d) - k + j]
                    parts.append(code)
            if not parts:
                break
            grams, times = np.unique(np.concatenate(parts), return_counts=True)
            owner = grams >> np.uint64(8)
            cuts = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))
            totals = np.add.reduceat(times, cuts)
            for a, b, total in zip(cuts.tolist(), [*cuts[1:].tolist(), len(grams)], totals.tolist(), strict=True):
                context = int(owner[a]).to_bytes(8, "big")[8 - k :] if k else b""
                if total >= least and (k == 0 or context[1:] in out):
                    row = np.zeros(256, np.int64)
                    row[(grams[a:b] & np.uint64(255)).astype(np.int64)] = times[a:b]
                    out[context] = row
        return out

    @staticmethod
    def _cost(tree: dict[bytes, np.ndarray], context: bytes) -> np.ndarray:
        """Code length in bits of every byte after ``context``."""
        while context not in tree:
            context = context[1:]
        cost, spent, offered = np.full(256, np.inf), 0.0, np.zeros(256, bool)
        while True:
            counts = np.where(offered, 0, tree[context])
            kinds, total = np.count_nonzero(counts), counts.sum()
            if kinds:
                here = counts > 0
                cost[here] = spent - np.log2(counts[here] / (total + kinds))
                spent -= np.log2(kinds / (total + kinds))
                offered |= here
            if not context:
                break
            context = context[1:]
        rest = ~offered
        cost[rest] = spent + np.log2(max(1, np.count_nonzero(rest)))
        return cost

    def code_lengths(self, raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Bits of each text (rows) in each language (columns)."""
        symbols = self.symbol[fold(raw)] if len(raw) > 1 else self.symbol[_FOLD[raw]]
        lengths = np.diff(offsets)
        lanes = -(-lengths // STRETCH)
        doc = np.repeat(np.arange(len(lengths)), lanes)
        turn = np.arange(len(doc)) - np.repeat(np.cumsum(lanes) - lanes, lanes)
        begin = offsets[doc] + turn * STRETCH
        end = np.minimum(begin + STRETCH, offsets[doc + 1])
        warm = np.minimum(self.order, begin - offsets[doc])  # the bytes before that fix the state
        order = np.argsort(-(end - begin + warm), kind="stable")
        doc, begin, end, warm = doc[order], begin[order], end[order], warm[order]
        at, todo = begin - warm, end - begin + warm
        state = np.zeros(len(doc), np.int64)
        bits = np.zeros((len(doc), len(self.names)))
        width = self.step.shape[1]
        step, cost = self.step.ravel(), self.bits.reshape(-1, len(self.names))
        for t in range(int(todo[0]) if len(todo) else 0):
            live = int(np.searchsorted(-todo, -t, "left"))
            cell = state[:live] * width + symbols[at[:live] + t]
            found = cost[cell]
            if t < self.order:
                found = np.where((warm[:live] > t)[:, None], 0, found)
            bits[:live] += found
            state[:live] = step[cell]
        out = np.zeros((len(lengths), len(self.names)))
        np.add.at(out, doc, bits)
        return out


def held_out(doc_id):
    """Rows that no model learns from."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def fit(docs: DataFrame, sample_docs: int = SAMPLE_DOCS, sample_chars: int = SAMPLE_CHARS) -> Model | None:
    """A model of every language of the labelled rows, from at most ``sample_docs`` documents each.

    Documents of over ``sample_chars`` characters come last, and only their first ``sample_chars`` are learned.
    """
    rows = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out(F.col("doc_id")))
    rows = rows.select("lang", "doc_id", F.xxhash64("text").alias("mark"), "text")
    order = Window.partitionBy("lang").orderBy(F.length("text") > sample_chars, F.xxhash64("doc_id"), "doc_id", "mark")
    chosen = rows.select("lang", "doc_id", "mark", F.row_number().over(order).alias("r")).where(F.col("r") <= sample_docs)  # keys only
    keys = ["lang", "doc_id", "mark"]
    found = rows.join(F.broadcast(chosen.select(*keys)), keys, "left_semi").groupBy(*keys).agg(F.first(F.substring("text", 1, sample_chars)).alias("text"))
    samples: dict[str, list[bytes]] = {}
    for lang, text in found.select("lang", "text").collect():  # equal rows count once, so the bound holds
        samples.setdefault(lang, []).append(text.encode("utf-8", "surrogatepass"))
    return Model(samples) if samples else None


def _letters(raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Whether each text has a letter."""
    ascii_letter = ((raw | 32) >= 97) & ((raw | 32) <= 122)
    sums = np.concatenate([[0], np.cumsum(ascii_letter)])
    out = sums[offsets[1:]] > sums[offsets[:-1]]
    for i in np.flatnonzero(~out):
        text = raw[offsets[i] : offsets[i + 1]].tobytes()
        if not text.isascii():
            out[i] = any(map(str.isalpha, text.decode("utf-8", "surrogatepass")))
    return out


def predict(docs: DataFrame, model: Model | None, keep: list[str] | None = None) -> DataFrame:
    """``keep`` columns (default doc_id) with lang_pred, score (posterior under equal priors) and bits_per_byte."""
    keep = keep or ["doc_id"]
    modest_batches(docs.sparkSession)
    held = docs.sparkSession.sparkContext.broadcast(model)
    inside = keep == ["_whole"]  # a packed row holds the text already
    rows = docs.select(*(F.col(c) for c in keep), *([] if inside else [F.col("text").alias("_text")]))
    kinds = {f.name: f.dataType.simpleString() for f in rows.schema}
    schema = ", ".join(f"`{c}` {kinds[c]}" for c in keep) + ", lang_pred string, score double, bits_per_byte double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = held.value
        for batch in batches:
            names, scores, rates = [], [], []
            for _, raw, offsets in texts(batch.column(0).field("text") if inside else batch.column(batch.num_columns - 1)):
                known = _letters(raw, offsets)
                if model is None:
                    known[:] = False
                bits = model.code_lengths(raw, offsets) if model else np.zeros((len(known), 1))
                best = bits.argmin(axis=1)
                least = bits[np.arange(len(best)), best]
                posterior = 1 / np.exp2(-np.minimum(bits - least[:, None], 1000)).sum(axis=1)
                names += [model.names[b] if k else "und" for b, k in zip(best.tolist(), known.tolist(), strict=True)]
                scores += np.where(known, posterior, 0.0).tolist()
                rates += np.where(known, least / np.maximum(1, np.diff(offsets)), 0.0).tolist()
            out = [pa.array(names, pa.string()), pa.array(scores, pa.float64()), pa.array(rates, pa.float64())]
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], *out], [*keep, "lang_pred", "score", "bits_per_byte"])
        pa.default_memory_pool().release_unused()

    return rows.mapInArrow(run, schema)


def identify(docs: DataFrame) -> DataFrame:
    """Per document: doc_id, held_out, lang_pred, score, bits_per_byte; learned on the rows that are not held out."""
    found = predict(docs, fit(docs))
    return found.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score", "bits_per_byte")


def accept(docs: DataFrame, least_score: float = 0.5, most_bits: float = 7.0) -> DataFrame:
    """Documents in a known language, all columns as they were: not ``und``, likelier than not, shorter coded than noise."""
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_whole"))  # no name of docs can clash
    found = predict(packed, fit(docs), keep=["_whole"])
    return found.where((F.col("lang_pred") != "und") & (F.col("score") >= least_score) & (F.col("bits_per_byte") <= most_bits)).select("_whole.*")
