"""BPE as a streaming transducer with bounded lookahead, and its inverse.

Merges apply in rank order.  What comes after a cut of the input can change tokens left
of it only through a chain of merges: one that straddles the cut, then later-ranked ones
that each begin further left, hold the left half of the one before and read the same text
where they meet.  The longest such chain gives the merge list's sufficient lookahead L: a token that ends L symbols
before the end of what has been read is final.  So a window of fixed size gives the exact
tokens of a word of any length: final tokens leave, the rest waits for more input.  The end of
a word makes all its tokens final.

A text passes through in blocks of ``BLOCK`` characters: ids of a block go to the digests and to the
decoder, then they are forgotten, so beside the row itself nothing grows with a text but the normalised
copy of its longest run without blanks.  Ids of short pieces are remembered, up to a
number of bytes a worker.  The decoder is a machine of its own that sees ids only.

``encode_table`` treats null text as empty text, keeps every row, and carries no other
column; an empty table gives an empty table.
"""

from __future__ import annotations

import codecs
import functools
import hashlib
import heapq
from array import array
from collections.abc import Iterable, Iterator
from itertools import chain, repeat

import pyarrow as pa
from pyspark.sql import DataFrame

from tolerant_gd.llm.store import modest_batches
from tolerant_gd.llm.wordbpe import PieceCache, WordBpe, byte_alphabet

#: Characters of a block of text; symbols that a streamed word hands on at once.
BLOCK, SLICE = 16_384, 4_096
#: Bytes of remembered pieces in each of the two generations that a Python worker holds.
CACHE = 32_000_000
_END = ""  # stands for the word-end suffix inside symbol strings


class MergeTransducer:
    """Ranked merges applied to one word's symbols, with memory bounded by ``window`` + lookahead."""

    def __init__(self, merges: list[tuple[str, str]], suffix: str = "", window: int = 512, lookahead: int = 0):
        self.suffix, self.window = suffix, window
        self.rank = {pair: i for i, pair in enumerate(merges)}
        self.product = [left + right for left, right in merges]
        self.lookahead = lookahead or sufficient_lookahead(plain_merges(merges, suffix))

    def _merge(self, symbols: list[str]) -> list[str]:
        """Apply merges in rank order, equal ranks from the left; may change the list."""
        if len(symbols) > 96:
            return self._merge_many(symbols)
        rank, product = self.rank.get, self.product
        never = len(product)
        ranks = list(map(rank, zip(symbols, symbols[1:]), repeat(never)))
        left = len(ranks)
        while left and (best := min(ranks)) < never:
            at = ranks.index(best)
            symbols[at] = whole = product[best]
            del symbols[at + 1], ranks[at]
            left -= 1
            if at:
                ranks[at - 1] = rank((symbols[at - 1], whole), never)
            if at < left:
                ranks[at] = rank((whole, symbols[at + 1]), never)
        return symbols

    def _merge_many(self, symbols: list[str]) -> list[str]:
        """The same over linked positions and a heap of (rank, position, pair)."""
        n, rank = len(symbols), self.rank
        after, before = [*range(1, n), -1], [-1, *range(n - 1)]
        heap = [(r, i, pair) for i, pair in enumerate(zip(symbols, symbols[1:])) if (r := rank.get(pair)) is not None]
        heapq.heapify(heap)
        while heap:
            r, i, (left, right) = heapq.heappop(heap)
            j = after[i]
            if symbols[i] != left or j < 0 or symbols[j] != right:
                continue  # one of the two has been merged since
            symbols[i], symbols[j], after[i] = self.product[r], "", after[j]
            if (k := after[i]) >= 0:
                before[k] = i
            for a, b in ((before[i], i), (i, k)):
                if a >= 0 and b >= 0 and (found := rank.get((symbols[a], symbols[b]))) is not None:
                    heapq.heappush(heap, (found, a, (symbols[a], symbols[b])))
        return [s for s in symbols if s]

    def word(self, symbols: str) -> list[str]:
        """Tokens of a whole word that fits the window: its end makes all of them final at once."""
        held = list(symbols)
        if held:
            held[-1] += self.suffix
        return self._merge(held)

    def tokens(self, symbols: Iterable[str]) -> Iterator[str]:
        """Tokens of one word, each as soon as it is final."""
        held: list[str] = []
        last = None
        for s in symbols:
            if last is not None:
                held.append(last)
                if len(held) >= self.window + self.lookahead:
                    final, done = len(held) - self.lookahead, 0
                    for token in self._merge(held[:]):
                        if done + len(token) > final:
                            break
                        done += len(token)
                        yield token
                    del held[:done]
            last = s
        if last is not None:
            held.append(last + self.suffix)
            yield from self._merge(held)


def plain_merges(merges: list[tuple[str, str]], suffix: str) -> list[tuple[str, str]]:
    """Merges with one character for the word end."""
    return [tuple(s.replace(suffix, _END) if suffix else s for s in pair) for pair in merges]


def sufficient_lookahead(merges: list[tuple[str, str]]) -> int:
    """An upper bound, in symbols, of how far left of a cut unseen input can change tokens.

    A later merge can only be given or denied by an earlier one that starts inside it, and both are read off the
    same text: from there on, one of the two strings begins with the other.
    """
    whole_reach: dict[str, int] = {}  # by merged string: how far left of the cut a chain that ends in it begins
    begin_reach: dict[str, int] = {}  # the most of that over merged strings that begin so, their left half included
    most = 1
    for left, right in merges:
        whole = left + right
        far = len(whole) - 1  # straddles the cut itself
        for at in range(1, len(whole)):
            before = begin_reach.get(whole[at:], 0)
            for end in range(at + 1, len(whole)):
                before = max(before, whole_reach.get(whole[at:end], 0))
            if before:
                far = max(far, before + at)
        most = max(most, far)
        whole_reach[whole] = max(far, whole_reach.get(whole, 0))
        for end in range(len(left), len(whole) + 1):
            if begin_reach.get(whole[:end], 0) < far:
                begin_reach[whole[:end]] = far
    return most


class TextDecoder:
    """Incremental tokens-to-text machine.

    ``joined``: tokens as they are written in the vocabulary, one blank between them (what the library
    does for files without a decoder).  ``bytes``: byte alphabet to UTF-8, word ends to blanks; a
    character cut by a token border waits for its other bytes.
    """

    def __init__(self, mode: str = "joined", suffix: str = "", token_of: dict[int, str] | None = None):
        self.mode, self.suffix, self.first, self.token_of = mode, suffix, True, token_of
        if mode == "bytes":
            self.utf8 = codecs.getincrementaldecoder("utf-8")(errors="replace")
            self.byte_of = {c: i for i, c in enumerate(byte_alphabet())}

    def feed(self, token: str) -> str:
        if self.mode == "joined":
            blank, self.first = "" if self.first else " ", False
            return blank + token
        ends = bool(self.suffix) and token.endswith(self.suffix)
        body = token.removesuffix(self.suffix) if ends else token
        return self.utf8.decode(bytes(self.byte_of[c] for c in body), ends) + " " * ends

    def feed_ids(self, ids: Iterable[int]) -> str:
        """What a run of ids adds to the text."""
        tokens = map(self.token_of.__getitem__, ids)
        if self.mode != "joined":
            return "".join(map(self.feed, tokens))
        text = " ".join(tokens)
        if not text:
            return ""
        blank, self.first = "" if self.first else " ", False
        return blank + text

    def close(self) -> str:
        return "" if self.mode == "joined" else self.utf8.decode(b"", True)


class Codec:
    """Whole-text encoding and decoding with one vocabulary file."""

    def __init__(self, path: str, lookahead: int = 0):
        self.bpe = WordBpe(path)
        self.machine = MergeTransducer(self.bpe.merges, self.bpe.suffix, lookahead=lookahead)
        self.vocab = self.bpe.vocab.__getitem__
        self.written = {i: str(i) for i in self.bpe.token_of}
        self.words = PieceCache(self._word, CACHE // 8, 8)  # word -> ids
        self.pieces = PieceCache(self._piece, CACHE, 8)  # run without blanks -> ids

    def _word(self, word: str) -> tuple[int, ...]:
        symbols = self.bpe.symbols(word)
        if len(symbols) <= self.machine.window:
            return tuple(map(self.vocab, self.machine.word(symbols)))
        return tuple(self._streamed(word))

    def _streamed(self, word: str) -> Iterator[int]:
        """Ids of one word, as they become final; symbols go in a slice at a time."""
        slices = (self.bpe.symbols(word[at : at + SLICE]) for at in range(0, len(word), SLICE))
        return map(self.vocab, self.machine.tokens(chain.from_iterable(slices)))

    def _piece(self, chunk: str) -> tuple[int, ...]:
        if two := self.bpe.stem_and_mark(chunk):
            return self.pieces[two[0]] + self.pieces[two[1]]
        words = self.bpe.words(chunk)
        if len(words) == 1:
            return self._word(words[0])
        return tuple(chain.from_iterable(map(self.words.__getitem__, words)))

    def _long(self, chunk: str) -> Iterator[list[int]]:
        """Ids of a run without blanks, whatever its length, some thousand at a time."""
        held: list[int] = []
        for word in self.bpe.each_word(chunk):
            for i in self._streamed(word) if len(word) > self.words.longest else self.words[word]:
                held.append(i)
                if len(held) >= SLICE:
                    yield held
                    held = []
        yield held

    def stream(self, text: str) -> Iterator[list[int]]:
        """Ids of a text in runs, in order; what has been handed out is not kept."""
        longest = self.pieces.longest
        for block in self.bpe.blocks(text, BLOCK):
            for special, s in self.bpe.segments(block):
                if special:
                    yield [self.bpe.added[s]]
                    continue
                chunks = self.bpe.chunks(s)
                at = 0
                if max(map(len, chunks), default=0) > longest:
                    for i, c in enumerate(chunks):
                        if len(c) > longest:
                            yield list(chain.from_iterable(map(self.pieces.__getitem__, chunks[at:i])))
                            yield from self._long(c)
                            at = i + 1
                yield list(chain.from_iterable(map(self.pieces.__getitem__, chunks[at:] if at else chunks)))

    def encode(self, text: str) -> list[int]:
        return list(chain.from_iterable(self.stream(text)))

    def decoder(self, mode: str = "joined") -> TextDecoder:
        return TextDecoder(mode, self.bpe.suffix, self.bpe.token_of)

    def decode(self, ids: Iterable[int], mode: str = "joined") -> str:
        machine = self.decoder(mode)
        return machine.feed_ids(ids) + machine.close()

    def forget(self) -> None:
        self.words.forget()
        self.pieces.forget()


@functools.cache
def codec(path: str, lookahead: int = 0) -> Codec:
    return Codec(path, lookahead)


def encode_table(docs: DataFrame, tokenizer: str, with_ids: bool = False) -> DataFrame:
    """Per document: doc_id, n_tokens, ids_sha256, decoded_sha256 and, as asked, ids and the decoded text."""
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<long>, decoded string" * with_ids
    names = [f.split()[0] for f in schema.split(", ")]
    modest_batches(docs.sparkSession)
    bpe = WordBpe(tokenizer)
    lookahead = sufficient_lookahead(plain_merges(bpe.merges, bpe.suffix))  # once, on the driver

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = codec(tokenizer, lookahead)
        written = machine.written.__getitem__
        for batch in batches:
            rows: list[list] = [[] for _ in names[1:]]
            for text in batch.column(1):
                n, back, coded, plain = 0, machine.decoder(), hashlib.sha256(), hashlib.sha256()
                kept, texts = array("q"), []
                for ids in machine.stream(text.as_py() or ""):
                    if not ids:
                        continue
                    decoded = back.feed_ids(ids)
                    coded.update(((" " if n else "") + " ".join(map(written, ids))).encode())
                    plain.update(decoded.encode("utf-8", "surrogatepass"))
                    n += len(ids)
                    if with_ids:
                        kept.extend(ids)
                        texts.append(decoded)
                plain.update(back.close().encode())
                values = [n, coded.hexdigest(), plain.hexdigest()]
                if with_ids:
                    values += [kept.tolist(), "".join(texts)]
                for column, v in zip(rows, values, strict=True):
                    column.append(v)
            kinds = [pa.int64(), pa.string(), pa.string(), pa.list_(pa.int64()), pa.string()]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(rows, kinds, strict=False))], names)
        pa.default_memory_pool().release_unused()

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(run, schema)
