"""Secret scans in DataFrame expressions: patterns, and entropy over sliding windows.

Base kinds (``assign``, ``access``, ``hex``) are pattern matches, leftmost and
non-overlapping per kind.  ``entropy`` spans come from candidate strings: runs of 20 or
more characters of an encoding alphabet that hold a letter and a digit.  A window of 20
slides over each; Shannon entropy follows from counts that change by one character out and
one in.  A candidate's character class (hex digits, letters and digits, all) sets the
entropy that a window must reach; the span runs from the first such window to the end of
the last.  Base spans are cut out of a candidate first: what is left on either side is a
candidate of its own if it has 20 characters.  Separators beside a cut do not count for its
class.  Candidates that match the allow-list are left out.

Offsets are code points, ends exclusive.  Null text is empty text and has no spans; ties in
start are ordered by kind as listed; every row gives a row.  No part runs in Python.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KINDS = ("assign", "access", "hex", "entropy")
# The patterns of the base kinds.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"(?<![0-9a-f])[0-9a-f]{32,}+"
#: Cheap conditions without which a kind cannot match.
ASSIGN_HINT = r"(?i)(?:passw(?:or)?d|secret|token|api_?key)[\"']?\x20*[:=]"

WINDOW = 20
CANDIDATE = rf"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{{{WINDOW},}}+"
CANDIDATE_HINT = rf"(?<![A-Za-z0-9+/_=-])(?=[A-Za-z+/_=-]*+[0-9])(?=[0-9+/_=-]*+[A-Za-z])[A-Za-z0-9+/_=-]{{{WINDOW},}}+"
#: (class, its pattern, least entropy of a window in bits); the first class that fits counts.
CLASSES = (("hex", "^[0-9a-fA-F]+$", 3.0), ("alphanumeric", "^[A-Za-z0-9]+$", 3.6), ("any", "", 3.75))
ALLOWED = (
    r"^[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}$",
    r"^[A-Za-z]*(?:[-_/=+]+[A-Za-z]+|[-_/=+]+[0-9]{1,6})*+[-_/=+]*$",
    r"(?i)example|sample|placeholder|dummy|changeme|0123456789|abcdefgh|(.)\1{5}",
)
#: Separators at the ends of a part.
EDGES = "^[+/_=-]++|(?<![+/_=-])[+/_=-]++$"
#: Long strings are held in pieces of so many characters, so that no step looks at a string from its start.
PIECE = 512
_XLOGX = [0.0] + [c * math.log2(c) for c in range(1, WINDOW + 1)]


def _lengths(text: Column, pattern: str, with_text: bool = False) -> Column:
    """For every match: the length of what lies between it and the one before, its own, and as asked its text in pieces."""
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    between = F.split(text, pattern, -1)  # one more than there are matches

    def both(b: Column, f: Column) -> Column:
        return F.struct(F.length(b).alias("gap"), F.length(f).alias("own"), *([_pieces(f).alias("text")] if with_text else []))

    return F.filter(F.zip_with(between, found, both), lambda x: x["own"].isNotNull())


def _pieces(s: Column) -> Column:
    return F.regexp_extract_all(s, F.lit(f"(?s).{{1,{PIECE}}}"), F.lit(0))


def _cut(pieces: Column, start: Column, end: Column) -> Column:
    """Characters start to end of a string held in pieces, in time of what is cut out."""
    a, b = F.floor(start / PIECE).cast("int"), F.floor((end - 1) / PIECE).cast("int")
    head = F.substring(F.get(pieces, a), start - a * PIECE + 1, F.least(end - start, F.lit(PIECE)))
    tail = F.substring(F.get(pieces, b), F.lit(1), end - b * PIECE)
    inner = F.array_join(F.slice(pieces, a + 2, F.greatest(b - a - 1, F.lit(0))), "")
    return F.when(end <= start, "").when(a == b, head).otherwise(F.concat(head, inner, tail))


def _spans(lengths: Column, kind: int, with_text: bool = False) -> Column:
    """Structs (start, kind, end) of all matches, as asked with their text in pieces."""
    start = F.struct(F.lit(0).alias("at"), (_no_runs() if with_text else _none()).alias("out"))

    def add(acc: Column, x: Column) -> Column:
        begin = acc["at"] + x["gap"]
        span = F.struct(begin.alias("start"), F.lit(kind).alias("kind"), (begin + x["own"]).alias("end"), *([x["text"].alias("text")] if with_text else []))
        return F.struct((begin + x["own"]).alias("at"), F.concat(acc["out"], F.array(span)).alias("out"))

    return F.aggregate(lengths, start, add)["out"]


def _no_runs() -> Column:
    return F.array().cast("array<struct<start:int,kind:int,end:int,text:array<string>>>")


def _only(spans: Column, flags: Column) -> Column:
    pairs = F.zip_with(spans, flags, lambda s, f: F.struct(s.alias("span"), f.alias("keep")))
    return F.transform(F.filter(pairs, lambda x: x["keep"]), lambda x: x["span"])


def _none() -> Column:
    return F.array().cast("array<struct<start:int,kind:int,end:int>>")


def _parts(base: Column, runs: Column) -> Column:
    """Structs (start, value, cut) of what base spans leave of runs, if long enough for a window, in one sweep by start."""
    no_text = F.array().cast("array<string>")
    marks = F.concat(F.transform(base, lambda b: F.struct(b["start"].alias("start"), b["kind"].alias("kind"), b["end"].alias("end"), no_text.alias("text"))), runs)
    stop = F.struct(F.lit(2**31 - 1).alias("start"), F.lit(3).alias("kind"), F.lit(2**31 - 1).alias("end"), no_text.alias("text"))
    marks = F.concat(F.array_sort(marks), F.array(stop))
    start = F.struct(F.lit(0).alias("at"), F.lit(0).alias("begin"), F.lit(0).alias("end"), F.lit(False).alias("cut"), F.lit(0).alias("covered"), no_text.alias("text"), F.array().cast("array<struct<start:int,value:string,cut:boolean>>").alias("out"))

    def step(acc: Column, x: Column) -> Column:
        run, to = x["kind"] == 3, F.least(x["start"], acc["end"])  # the open run is settled up to here
        touches = ~run & (x["start"] < acc["end"]) & (x["end"] > acc["begin"])
        whole = F.struct(acc["at"].alias("start"), _cut(acc["text"], acc["at"] - acc["begin"], to - acc["begin"]).alias("value"), (acc["cut"] | touches).alias("cut"))
        done = (run | touches | (x["start"] >= acc["end"])) & (to - acc["at"] >= WINDOW)
        covered = F.greatest(acc["covered"], F.when(run, 0).otherwise(x["end"]))
        return F.struct(
            F.when(run, F.greatest(x["start"], acc["covered"])).otherwise(F.greatest(acc["at"], F.when(touches, x["end"]).otherwise(to))).alias("at"),
            F.when(run, x["start"]).otherwise(acc["begin"]).alias("begin"),
            F.when(run, x["end"]).otherwise(acc["end"]).alias("end"),
            F.when(run, acc["covered"] > x["start"]).otherwise(acc["cut"] | touches).alias("cut"),
            covered.alias("covered"),
            F.when(run, x["text"]).otherwise(acc["text"]).alias("text"),
            F.when(done, F.concat(acc["out"], F.array(whole))).otherwise(acc["out"]).alias("out"),
        )

    return F.aggregate(marks, start, step)["out"]


def _let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once, however often the body (and steps within it) use it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _entropy_bounds(s: Column, cut: Column) -> Column:
    """(first, last) start of windows of ``s`` whose entropy reaches the class's bound; first is -1 if none does."""

    def bound(inner: Column) -> Column:
        least = F.lit(CLASSES[-1][2])
        for _, pattern, bits in reversed(CLASSES[:-1]):
            least = F.when(inner.rlike(pattern), F.lit(bits)).otherwise(least)
        return (F.lit(math.log2(WINDOW)) - least) * WINDOW + 1e-9  # of the sum of c log2 c

    def search(x: Column) -> Column:
        # each piece with the characters of the next one that its last windows reach into
        reaching = F.transform(x["pieces"], lambda p, i: F.struct((i * PIECE).alias("at"), F.concat(p, F.coalesce(F.substring(F.get(x["pieces"], i + 1), 1, WINDOW - 1), F.lit(""))).alias("s")))
        found = F.transform(F.filter(reaching, lambda p: F.length(p["s"]) >= WINDOW), lambda p: F.struct(p["at"].alias("at"), _slide(p["s"], x["most"]).alias("b")))
        return F.filter(found, lambda p: p["b"]["first"] >= 0)

    def ends(hits: Column) -> Column:
        first, last = F.get(hits, F.lit(0)), F.get(hits, F.size(hits) - 1)
        return F.struct(F.coalesce(first["at"] + first["b"]["first"], F.lit(-1)).alias("first"), F.coalesce(last["at"] + last["b"]["last"], F.lit(-1)).alias("last"))

    most = _let(F.when(cut, F.regexp_replace(s, EDGES, "")).otherwise(s), bound)
    return _let(_let(F.struct(_pieces(s).alias("pieces"), most.alias("most")), search), ends)


def _slide(s: Column, most: Column) -> Column:
    """The window over one piece: it loses a character and gains one a step, and the sum changes by their counts."""
    table = F.array(*[F.lit(v) for v in _XLOGX])

    def count(window: Column, c: Column) -> Column:
        return F.length(window) - F.length(F.replace(window, c))

    def run(chars: Column) -> Column:
        first = F.substring(s, 1, WINDOW)
        whole = F.aggregate(F.array_distinct(F.slice(chars, 1, WINDOW)), F.lit(0.0), lambda a, c: a + F.get(table, count(first, c)))
        start = _let(whole, lambda v: F.struct(v.alias("sum"), F.when(v <= most, 0).otherwise(-1).alias("first"), F.when(v <= most, 0).otherwise(-1).alias("last"), first.alias("window")))
        steps = F.when(F.length(s) > WINDOW, F.sequence(F.lit(1), F.length(s) - WINDOW)).otherwise(F.array().cast("array<int>"))
        return F.aggregate(steps, start, lambda acc, i: slide(chars, acc, i))

    def slide(chars: Column, acc: Column, i: Column) -> Column:
        window, gone, new = acc["window"], F.substring(acc["window"], 1, 1), F.get(chars, i + (WINDOW - 1))
        out_n = count(window, gone)
        in_n = count(window, new) - (gone == new).cast("int")
        change = F.get(table, out_n - 1) - F.get(table, out_n) + F.get(table, in_n + 1) - F.get(table, in_n)

        def after(total: Column) -> Column:
            ok = total <= most
            return F.struct(total.alias("sum"), F.when(ok & (acc["first"] < 0), i).otherwise(acc["first"]).alias("first"), F.when(ok, i).otherwise(acc["last"]).alias("last"), F.concat(F.substring(window, 2, WINDOW - 1), new).alias("window"))

        return _let(acc["sum"] + change, after)

    return _let(F.split(s, ""), run)


def scan(docs: DataFrame, keep: list[str] | None = None) -> DataFrame:
    """``keep`` columns (default doc_id) with ``base`` and ``found``: arrays of (start, kind, end), in order."""
    keep = keep or ["doc_id"]
    text = F.coalesce(F.col("_text"), F.lit(""))
    rows = docs.select(*keep, F.col("text").alias("_text"))
    long_value = F.transform(F.regexp_extract_all(text, F.lit(ASSIGN), F.lit(2)), lambda v: F.length(v) >= 8)
    long_access = F.transform(F.regexp_extract_all(text, F.lit(ACCESS), F.lit(0)), lambda v: F.length(v) >= 16)
    none, no_flags = F.array().cast("array<struct<gap:int,own:int>>"), F.array().cast("array<boolean>")
    rows = rows.select(
        *keep,
        "_text",
        F.when(text.rlike(ASSIGN_HINT), _lengths(text, ASSIGN)).otherwise(none).alias("_assign"),
        F.when(text.rlike(ASSIGN_HINT), long_value).otherwise(no_flags).alias("_assign_ok"),
        F.when(text.contains("AKIA"), _lengths(text, ACCESS)).otherwise(none).alias("_access"),
        F.when(text.contains("AKIA"), long_access).otherwise(no_flags).alias("_access_ok"),
        F.when(text.rlike(HEX), _lengths(text, HEX)).otherwise(none).alias("_hex"),
        F.when(text.rlike(CANDIDATE_HINT), _lengths(text, CANDIDATE, True)).alias("_runs"),
    )
    base = F.concat(_only(_spans(F.col("_assign"), 0), F.col("_assign_ok")), _only(_spans(F.col("_access"), 1), F.col("_access_ok")), _spans(F.col("_hex"), 2))
    rows = rows.select(*keep, "_text", F.array_sort(base).alias("base"), F.when(F.size("_runs") > 0, _spans(F.col("_runs"), 3, True)).alias("_runs"))
    rows = rows.select(*keep, "_text", "base", F.when(F.col("_runs").isNotNull(), _parts(F.col("base"), F.col("_runs"))).alias("_parts"))

    def wanted(r: Column) -> Column:
        fine = r["value"].rlike("[0-9]") & r["value"].rlike("[A-Za-z]")
        for pattern in ALLOWED:
            fine = fine & ~r["value"].rlike(pattern)
        return fine

    bounds = F.transform(F.filter("_parts", wanted), lambda r: F.struct(r["start"].alias("start"), _entropy_bounds(r["value"], r["cut"]).alias("b")))
    rows = rows.select(*keep, "_text", "base", F.when(F.size("_parts") > 0, bounds).alias("_bounds"))
    entropy = F.transform(F.filter("_bounds", lambda x: x["b"]["first"] >= 0), lambda x: F.struct((x["start"] + x["b"]["first"]).alias("start"), F.lit(3).alias("kind"), (x["start"] + x["b"]["last"] + WINDOW).alias("end")))
    return rows.select(*keep, "_text", "base", F.array_sort(F.concat("base", F.coalesce(entropy, _none()))).alias("found"))


def written(spans: str) -> Column:
    """kind:start:end of all spans, comma-joined."""
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))))


def report(docs: DataFrame) -> DataFrame:
    """Per document: doc_id, counts of base kinds, digest of base spans, all spans."""

    def count(kind: int) -> Column:
        return F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{KINDS[kind]}")

    counts = [count(i) for i in range(3)]
    return scan(docs).select("doc_id", *counts, F.sha2(written("base"), 256).alias("base_sha256"), written("found").alias("spans"))


def redact(docs: DataFrame, mask: str = "[SECRET]") -> DataFrame:
    """All documents with every span replaced by ``mask``; n_chars, where there is one, follows the text."""
    columns = docs.columns
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in columns]).alias("_row"), "text")  # no name of docs can clash
    found = scan(packed, ["_row"])
    # spans united where they overlap: what stays is the text between neighbours
    none = F.array().cast("array<struct<start:int,end:int>>")

    def unite(acc: Column, x: Column) -> Column:
        inside = x["start"] < acc["end"]
        return F.struct(
            F.when(inside, acc["start"]).otherwise(x["start"]).alias("start"),
            F.when(inside, F.greatest(acc["end"], x["end"])).otherwise(x["end"]).alias("end"),
            F.when(inside, acc["out"]).otherwise(F.concat(acc["out"], F.array(F.struct(acc["start"].alias("start"), acc["end"].alias("end"))))).alias("out"),
        )

    united = F.aggregate("found", F.struct(F.lit(0).alias("start"), F.lit(0).alias("end"), none.alias("out")), unite)
    found = found.select("_row", "_text", F.when(F.size("found") > 0, united).alias("_u"), F.when(F.size("found") > 0, _pieces(F.col("_text"))).alias("_pieces"))
    found = found.select("_row", "_text", "_pieces", F.concat("_u.out", F.array(F.struct(F.col("_u.start").alias("start"), F.col("_u.end").alias("end")))).alias("_spans"))
    nexts = F.concat(F.transform(F.slice("_spans", 2, F.size("_spans")), lambda x: x["start"]), F.array(F.length("_text")))
    between = F.zip_with("_spans", nexts, lambda x, to: _cut(F.col("_pieces"), x["end"], to))  # the first one is the empty span at 0
    clean = found.select("_row", F.when(F.col("_spans").isNull(), F.col("_text")).otherwise(F.array_join(between, mask)).alias("_clean"))
    out = {c: F.col("_row").getField(c) for c in columns} | {"text": F.col("_clean")}
    if "n_chars" in columns:
        out["n_chars"] = F.when(F.col("_clean").isNull(), out["n_chars"]).otherwise(F.length("_clean")).cast(docs.schema["n_chars"].dataType)
    return clean.select(*[out[c].alias(c) for c in columns])
