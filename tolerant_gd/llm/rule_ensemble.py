"""Quality classifier as a sparse rule ensemble, compiled into Spark expressions.

Statistics of the whole text (native expressions) are the inputs.  On a bounded sample of
labelled documents, small trees are grown one after another on what the ones before leave
unexplained; every path from a root to a node becomes a rule, a conjunction of bounds on
statistics.  A lasso logistic regression over all rules keeps few of them with weights.
The kept rules become one column expression, so scoring runs in the JVM like any filter.

Null or empty text has all statistics zero and is scored like any text.  Rows without a
quality label do not train; several labels of a document all count; every document gives a
row.  With no labelled row, or only one class, the score is the share of good labels (0.5
without any).
"""

from __future__ import annotations

import math
from typing import NamedTuple

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tolerant_gd.llm.ppm_language import held_out

#: Bound of the training sample, in labelled documents.
SAMPLE_DOCS = 6_000
TREES, DEPTH, CUTS, LEAST_ROWS, PENALTY = 30, 3, 24, 20, 0.004
THRESHOLD = 0.7
LETTERS_UP = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
MARKS = "#$%&*+<=>@[]^_`{|}~\\"


def statistics(text: Column) -> dict[str, Column]:
    """Named statistics of whole texts."""
    t = F.coalesce(text, F.lit(""))
    chars = F.length(t)
    words = F.filter(F.split(t, r"[ \n\t\r]+"), lambda w: w != "")
    lines = F.split(t, "\n")

    def share(part: Column, whole: Column) -> Column:
        return F.when(whole > 0, part / whole).otherwise(F.lit(0.0))

    def held(letters: str) -> Column:
        return share(chars - F.length(F.translate(t, letters, "")), chars)

    return {
        "log_chars": F.log1p(chars),
        "log_words": F.log1p(F.size(words)),
        "word_length": share(chars, F.size(words)),
        "upper": held(LETTERS_UP),
        "digits": held("0123456789"),
        "marks": held(MARKS),
        "bangs": held("!?"),
        "stops": held(".,;:"),
        "distinct_words": share(F.size(F.array_distinct(words)), F.size(words)),
        "distinct_lines": share(F.size(F.array_distinct(lines)), F.size(lines)),
        "doubled_words": share(F.regexp_count(t, F.lit(r"(?<!\S)(\S++) (?=\1(?!\S))")), F.size(words)),
        "bars": held("|"),
    }


class Rule(NamedTuple):
    """A conjunction of (statistic, at most?, bound)."""

    bounds: tuple[tuple[int, bool, float], ...]

    def holds(self, x: np.ndarray) -> np.ndarray:
        out = np.ones(len(x), bool)
        for j, below, cut in self.bounds:
            out &= (x[:, j] <= cut) == below
        return out

    def column(self, names: list[str]) -> Column:
        out = F.lit(True)
        for j, below, cut in self.bounds:
            c = F.col(names[j])
            out = out & ((c <= F.lit(cut)) if below else (c > F.lit(cut)))
        return out


def _grow(x: np.ndarray, target: np.ndarray, rows: np.ndarray, cuts: list[np.ndarray], path: tuple, depth: int, rules: list[Rule], out: np.ndarray) -> None:
    """Least-squares tree on ``target``; collects the rule of every node and adds leaf means to ``out``."""
    if path:
        rules.append(Rule(path))
    y = target[rows]
    best = None
    if depth and len(rows) >= 2 * LEAST_ROWS:
        total, n = y.sum(), len(rows)
        for j, c in enumerate(cuts):
            bins = np.searchsorted(c, x[rows, j], "left")
            counts = np.bincount(bins, minlength=len(c) + 1).cumsum()[:-1]
            sums = np.bincount(bins, y, minlength=len(c) + 1).cumsum()[:-1]
            ok = (counts >= LEAST_ROWS) & (n - counts >= LEAST_ROWS)
            gain = np.where(ok, sums**2 / np.maximum(counts, 1) + (total - sums) ** 2 / np.maximum(n - counts, 1) - total**2 / n, -1)
            if len(gain) and gain.max() > 1e-6 and (best is None or gain.max() > best[0]):
                best = (gain.max(), j, float(c[gain.argmax()]))
    if best is None:
        out[rows] = y.mean()
        return
    _, j, cut = best
    below = x[rows, j] <= cut
    _grow(x, target, rows[below], cuts, (*path, (j, True, cut)), depth - 1, rules, out)
    _grow(x, target, rows[~below], cuts, (*path, (j, False, cut)), depth - 1, rules, out)


def grow_rules(x: np.ndarray, y: np.ndarray, trees: int = TREES, seed: int = 7) -> list[Rule]:
    random = np.random.default_rng(seed)
    cuts = [np.unique(np.quantile(x[:, j], np.linspace(0.02, 0.98, CUTS))) for j in range(x.shape[1])]
    logit, rules = np.full(len(y), math.log(y.mean() / (1 - y.mean()))), []
    for _ in range(trees):
        part = np.flatnonzero(random.random(len(y)) < 0.5)
        if len(part) < 2 * LEAST_ROWS:
            part = np.arange(len(y))
        residual, step, grown = y - 1 / (1 + np.exp(-logit)), np.zeros(len(y)), []
        _grow(x, residual, part, cuts, (), DEPTH, grown, step)
        rules += grown
        logit += 3.0 * _spread(step, part, grown, x)
    return list(dict.fromkeys(rules))


def _spread(step: np.ndarray, part: np.ndarray, grown: list[Rule], x: np.ndarray) -> np.ndarray:
    """Leaf values for all rows, from those of the rows that grew the tree."""
    out = np.zeros(len(x))
    mine = np.zeros(len(x), bool)
    mine[part] = True
    for r in grown:  # parents come before children, so leaves have the last word
        held = r.holds(x)
        out[held] = step[held & mine].mean()
    return out


def lasso_logistic(z: np.ndarray, y: np.ndarray, penalty: float = PENALTY, rounds: int = 400) -> tuple[float, np.ndarray]:
    """Intercept and weights of least penalised log-loss, by accelerated proximal gradient on scaled columns."""
    scale = np.maximum(z.std(axis=0), 0.05)
    zs = (z - z.mean(axis=0)) / scale
    n, d = zs.shape
    v = np.ones(d)
    for _ in range(30):
        v = zs.T @ (zs @ v)
        v /= np.linalg.norm(v) + 1e-12
    step = 4 * n / (np.linalg.norm(zs @ v) ** 2 + n)
    w, b = np.zeros(d), math.log(y.mean() / (1 - y.mean()))
    wa, ba, t = w, b, 1.0
    for _ in range(rounds):
        err = 1 / (1 + np.exp(-(zs @ wa + ba))) - y
        w_new = wa - step * (zs.T @ err) / n
        w_new = np.sign(w_new) * np.maximum(np.abs(w_new) - step * penalty, 0)
        b_new = ba - step * err.mean()
        t_new = (1 + math.sqrt(1 + 4 * t * t)) / 2
        wa, ba = w_new + (t - 1) / t_new * (w_new - w), b_new + (t - 1) / t_new * (b_new - b)
        w, b, t = w_new, b_new, t_new
    weights = w / scale
    return float(b - weights @ z.mean(axis=0)), weights


class RuleModel(NamedTuple):
    names: list[str]
    bias: float
    rules: list[tuple[Rule, float]]

    def score(self) -> Column:
        """The compiled score, over columns named like the statistics."""
        total = F.lit(self.bias)
        for rule, weight in self.rules:
            total = total + F.when(rule.column(self.names), F.lit(weight)).otherwise(F.lit(0.0))
        return 1 / (1 + F.exp(-total))

    def apply(self, x: np.ndarray) -> np.ndarray:
        total = np.full(len(x), self.bias)
        for rule, weight in self.rules:
            total += weight * rule.holds(x)
        return 1 / (1 + np.exp(-total))


def fit_arrays(x: np.ndarray, y: np.ndarray, names: list[str]) -> RuleModel:
    if len(y) == 0 or y.min() == y.max():
        good = (y.sum() + 0.5) / (len(y) + 1)
        return RuleModel(names, float(math.log(good / (1 - good))), [])
    rules = grow_rules(x, y)
    if not rules:
        return RuleModel(names, math.log(y.mean() / (1 - y.mean())), [])
    z = np.stack([r.holds(x) for r in rules], axis=1).astype(float)
    bias, weights = lasso_logistic(z, y)
    return RuleModel(names, bias, [(r, float(w)) for r, w in zip(rules, weights, strict=True) if abs(w) > 1e-9])


def fit(docs: DataFrame, labels: DataFrame, sample_docs: int = SAMPLE_DOCS) -> RuleModel:
    """Learn from at most ``sample_docs`` labelled documents, those of least hash, that are not held out."""
    names = list(statistics(F.lit("")))
    some = labels.where(F.col("quality").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).select("doc_id", "quality")
    some = some.orderBy(F.xxhash64("doc_id"), "doc_id", "quality").limit(sample_docs)
    rows = docs.select("doc_id", "text").join(F.broadcast(some), "doc_id")
    stats = [c.cast("double").alias(n) for n, c in statistics(F.col("text")).items()]
    # several rows may have one doc_id: the bound holds for rows too, by the same order and not by the order of ids
    chosen = rows.select(F.xxhash64("doc_id").alias("_h"), F.xxhash64("text", "quality").alias("_t"), "doc_id", "quality", *stats)
    got = sorted(tuple(r)[2:] for r in chosen.orderBy("_h", "doc_id", "_t").limit(sample_docs).collect())
    data = np.array([r[2:] for r in got], float).reshape(len(got), len(names))
    return fit_arrays(data, np.array([float(r[1] == 1) for r in got]), names)


def score(docs: DataFrame, model: RuleModel) -> DataFrame:
    """Per document: doc_id, held_out, score, predicted."""
    stats = docs.select("doc_id", *[c.cast("double").alias(n) for n, c in statistics(F.col("text")).items()])
    scored = stats.select("doc_id", model.score().alias("score"))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
