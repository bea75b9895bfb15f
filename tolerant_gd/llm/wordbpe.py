"""Pre-tokenisation and byte-level alphabet of word-end BPE vocabularies.

Understands tokenizer files of one shape: NFC, white space to blank, lower case;
a removing regex split into contractions, letter runs, single numerals and symbol
runs; bytes as printable characters; merges with a word-end suffix.  Anything else
raises ``ValueError`` so that no file is silently tokenised in the wrong way.
"""

from __future__ import annotations

import functools
import json
import re
import sys
import unicodedata
from collections.abc import Iterator

SPACE = "\\t-\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"
CONTRACTIONS = ("'s", "'t", "'re", "'ve", "'m", "'ll", "'d")
_PATTERN = "|".join(CONTRACTIONS) + r"|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
_CHUNK = re.compile(f"[^{SPACE}]+")
_ODD_SPACE = re.compile("[\x1c-\x1f]")  # str.split() takes these for blanks


def _ranges(kind: str) -> str:
    """A regex class body of all code points whose category starts with ``kind``."""
    out, first = [], None
    for cp in range(sys.maxunicode + 2):
        inside = cp <= sys.maxunicode and unicodedata.category(chr(cp))[0] == kind
        if inside and first is None:
            first = cp
        elif not inside and first is not None:
            out.append(f"\\U{first:08x}-\\U{cp - 1:08x}")
            first = None
    return "".join(out)


@functools.cache
def word_pattern() -> re.Pattern:
    letters, numerals = _ranges("L"), _ranges("N")
    return re.compile("|".join(CONTRACTIONS) + f"|[{letters}]+|[{numerals}]|[^{SPACE}{letters}{numerals}]+")


@functools.cache
def byte_alphabet() -> tuple[str, ...]:
    """The printable stand-in of each byte: itself where visible, else code points from 256 on."""
    visible = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return tuple(chr(b) if b in visible else chr(next(spare)) for b in range(256))


class WordBpe:
    """A parsed tokenizer file: vocabulary, merges, added tokens, word splitting."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        steps = [n["type"] for n in (spec["normalizer"] or {}).get("normalizers", [])]
        split = (spec["pre_tokenizer"] or {}).get("pretokenizers", [{}])
        known = (
            model["type"] == "BPE"
            and steps == ["NFC", "Replace", "Lowercase"]
            and [p.get("type") for p in split] == ["Split", "ByteLevel"]
            and split[0]["pattern"].get("Regex") == _PATTERN
            and split[0]["behavior"] == "Removed"
            and split[0]["invert"]
            and not split[1]["add_prefix_space"]
            and not split[1]["use_regex"]
            and not any(model.get(k) for k in ("dropout", "unk_token", "continuing_subword_prefix", "byte_fallback", "ignore_merges"))
            and spec.get("decoder") is None
        )
        if not known:
            raise ValueError(f"not a word-end BPE file of the supported shape: {path}")
        self.path = path
        self.suffix = model.get("end_of_word_suffix") or ""
        self.vocab: dict[str, int] = model["vocab"]
        self.merges = [tuple(m.split(" ", 1)) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        self.added = {t["content"]: t["id"] for t in spec["added_tokens"]}
        if any(t["normalized"] or t["single_word"] or t["lstrip"] or t["rstrip"] for t in spec["added_tokens"]):
            raise ValueError("added tokens must be plain strings")
        self.token_of = {i: t for t, i in self.vocab.items()} | {i: t for t, i in self.added.items()}
        longest_first = sorted(self.added, key=len, reverse=True)
        self._added = re.compile("(" + "|".join(map(re.escape, longest_first)) + ")") if longest_first else None

    def segments(self, text: str) -> list[tuple[bool, str]]:
        """(is an added token, string) in text order; added tokens are found before normalisation."""
        if self._added is None or not any(t in text for t in self.added):
            return [(False, text)]
        return [(bool(i % 2), s) for i, s in enumerate(self._added.split(text)) if s]

    @staticmethod
    def normalise(text: str) -> str:
        if not unicodedata.is_normalized("NFC", text):
            text = unicodedata.normalize("NFC", text)
        if "Σ" in text:  # lower() would choose the final form by context
            text = text.replace("Σ", "σ")
        return text.lower()

    def chunks(self, text: str) -> list[str]:
        """Blank-separated pieces of a normalised segment; words never cross them."""
        text = self.normalise(text)
        return _CHUNK.findall(text) if _ODD_SPACE.search(text) else text.split()

    @functools.cached_property
    def library(self):
        from tokenizers import Tokenizer

        return Tokenizer.from_file(self.path)

    def words(self, chunk: str) -> list[str]:
        """Words of one chunk.  Code points that this Python does not know as assigned are left to the library."""
        if chunk.isascii():
            return [chunk] if chunk.isalpha() else word_pattern().findall(chunk)
        if any(unicodedata.category(c) == "Cn" for c in chunk):
            steps = self.library
            found = steps.pre_tokenizer.pre_tokenize_str(steps.normalizer.normalize_str(chunk))
            back = {c: b for b, c in enumerate(byte_alphabet())}
            return [bytes(back[c] for c in w).decode("utf-8", "surrogatepass") for w, _ in found]
        return word_pattern().findall(chunk)

    def each_word(self, chunk: str) -> Iterator[str]:
        """``words``, one at a time; for chunks of any length."""
        if len(chunk) <= 64 or not chunk.isascii() and any(unicodedata.category(c) == "Cn" for c in chunk):
            yield from self.words(chunk)
        else:
            for m in word_pattern().finditer(chunk):
                yield m.group()

    @staticmethod
    def stem_and_mark(chunk: str) -> tuple[str, str] | None:
        """A chunk of ASCII letters and one closing mark, as its two words; None for other chunks."""
        if len(chunk) > 1 and chunk.isascii() and not chunk[-1].isalnum() and chunk[:-1].isalpha():
            return chunk[:-1], chunk[-1]
        return None

    def blocks(self, text: str, size: int) -> Iterator[str]:
        """The text in runs of about ``size`` characters, cut before blanks of ASCII, which nothing composes with."""
        at = 0
        while len(text) - at > size:
            end = text.rfind(" ", at + 1, at + size)
            if end < 0:
                end = text.find(" ", at + size)
            if end < 0:
                break
            yield text[at:end]
            at = end
        yield text[at:] if at else text

    @staticmethod
    def symbols(word: str) -> str:
        """The word in the byte alphabet, one character per UTF-8 byte."""
        if word.isascii() and word.isalnum():
            return word
        table = byte_alphabet()
        return "".join([table[b] for b in word.encode("utf-8", "surrogatepass")])


class PieceCache(dict):
    """chunk -> encoded value, filled on demand; two generations of at most ``limit`` bytes each, by estimate.

    When the young generation is full it becomes the old one; what is still in use moves back from there.
    Keys of over ``longest`` characters are made anew each time.  ``per_item`` is the size of one item of a value.
    """

    ENTRY = 200  # table slots, the key's and the value's own heads

    def __init__(self, make, limit: int = 12_000_000, per_item: int = 1, longest: int = 64):
        super().__init__()
        self.make, self.limit, self.per_item, self.longest, self.old, self.held = make, limit, per_item, longest, {}, 0

    def __missing__(self, key: str):
        value = self.old.get(key)
        if value is None:
            value = self.make(key)
        size = len(key)
        if size <= self.longest:
            if self.held > self.limit:
                self.old, self.held = dict(self), 0
                self.clear()
            self[key] = value
            self.held += self.ENTRY + size + self.per_item * len(value)
        return value

    def forget(self) -> None:
        self.old, self.held = {}, 0
        self.clear()
