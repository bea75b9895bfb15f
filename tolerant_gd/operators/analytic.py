"""Completion-time statistics in closed form.

Two kinds: a number of complete workers (binomial tail), and a number of messages
(multinomial over how much each worker has done; by enumeration where there are few
compositions, by K-fold convolution otherwise).  Means integrate the complement.
"""

from __future__ import annotations

from collections.abc import Callable
from math import comb, factorial

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tolerant_gd.functions.latency import cdf_shifted
from tolerant_gd.plans.scheme import Scheme, message_threshold

ENUMERATE = 100_000
#: Up to so many compositions enumeration takes less time than convolution; both are exact.
QUICKER = 100


def done_probabilities(r: int, t: float, rate: float = 10.0, shift: float = 0.01) -> np.ndarray:
    """Probability that a worker has done exactly s = 0..r computations by t."""
    f = [1.0] + [cdf_shifted(rate, shift, s, t) for s in range(1, r + 1)] + [0.0]
    return np.array([f[s] - f[s + 1] for s in range(r + 1)])


def cdf_workers(K: int, r: int, need: int, t: float, rate: float = 10.0, shift: float = 0.01) -> float:
    p = cdf_shifted(rate, shift, r, t)
    return sum(comb(K, n) * p**n * (1 - p) ** (K - n) for n in range(need, K + 1))


def compositions(K: int, parts: int):
    if parts == 1:
        yield (K,)
        return
    for n in range(K + 1):
        for rest in compositions(K - n, parts - 1):
            yield (n, *rest)


def cdf_messages(K: int, r: int, need: int, t: float, how: str = "auto", weight: Callable[[int], int] = lambda s: s, rate: float = 10.0, shift: float = 0.01) -> float:
    """Probability that ``need`` messages have come when a worker with s computations has sent ``weight(s)``."""
    p = done_probabilities(r, t, rate, shift)
    if how == "auto":
        how = "enumerate" if comb(K + r, r) <= QUICKER else "convolve"
    if how == "enumerate":
        total = 0.0
        for n in compositions(K, r + 1):
            if sum(weight(s) * c for s, c in enumerate(n)) >= need:
                ways = factorial(K)
                for c in n:
                    ways //= factorial(c)
                total += ways * float(np.prod(p ** np.array(n)))
        return total
    one = np.zeros(max(weight(s) for s in range(r + 1)) + 1)
    for s in range(r + 1):
        one[weight(s)] += p[s]
    total = np.ones(1)
    for _ in range(K):
        total = np.convolve(total, one)
    return float(total[need:].sum())


def cdf(s: Scheme, t: float, rate: float = 10.0, shift: float = 0.01) -> float:
    """Closed form for every scheme with a count threshold; coverage schemes have none and raise."""
    need = message_threshold(s)
    if s.name in ("gradcode_single", "lagrange_single", "first_workers", "wait_all", "gradcode_repeat"):
        one = cdf_workers(s.size, s.r, need, t, rate, shift)
    elif s.name == "lagrange_multi":
        one = cdf_messages(s.K, s.r, need, t, "auto", lambda n: n // s.polys, rate, shift)
    elif s.name == "gradcode_layered":
        one = cdf_messages(s.size, s.r, need, t, "auto", lambda n: sum(m <= n for m in s.orders), rate, shift)
    else:
        raise ValueError(f"{s.name} ends on coverage, not on a count; simulate it")
    return one**s.P


def expected_completion(f: Callable[[float], float], upper: float = 8.0, step: float = 0.0005) -> float:
    """Integral of 1 - CDF by the trapezoid rule."""
    t = np.arange(0, upper + step, step)
    y = np.array([1 - f(x) for x in t])
    return float(((y[1:] + y[:-1]) / 2 * step).sum())


def harmonic(K: int, need: int) -> float:
    """Mean of the need-th smallest of K exponentials of mean one."""
    return sum(1 / i for i in range(K - need + 1, K + 1))


def expected_workers(K: int, r: int, need: int, rate: float = 10.0, shift: float = 0.01) -> float:
    """Mean of the need-th smallest of K shifted exponentials of r computations."""
    return r * (shift + harmonic(K, need) / rate)


def _grid(spark: SparkSession, points: int, rate: float, shift: float, fit: DataFrame | None):
    """Points (id), rate and shift: numbers, or columns from the one row of ``fit``."""
    if fit is None:
        return spark.range(points), rate, shift
    rate = F.when(F.col("excess") == 0, float("inf")).otherwise(1 / F.col("excess"))  # times that are all alike: a step
    return spark.range(points).crossJoin(F.broadcast(fit.select("shift", "excess"))), rate, F.col("shift")


def worker_cdf_table(spark: SparkSession, K: int, r: int, need: int, points: int, step: float, rate: float = 10.0, shift: float = 0.01, fit: DataFrame | None = None) -> DataFrame:
    """k, cdf over a grid, as a plan: tail terms are a small broadcast table.  One row of ``fit`` (shift, excess) replaces rate and shift."""
    grid, rate, shift = _grid(spark, points, rate, shift, fit)
    terms = spark.createDataFrame([(n, float(comb(K, n))) for n in range(need, K + 1)], "n int, ways double")
    t = F.col("id") * step
    p = F.when(t <= r * shift, 0.0).otherwise(1 - F.exp(-rate * (t / r - shift)))
    rows = grid.select(F.col("id").alias("k"), t.alias("t"), p.alias("p")).join(F.broadcast(terms))
    term = F.col("ways") * F.pow("p", F.col("n")) * F.pow(1 - F.col("p"), K - F.col("n"))
    return rows.groupBy("k", "t").agg(F.round(F.sum(term), 8).alias("cdf")).select("k", "cdf")


def message_cdf_table(spark: SparkSession, K: int, r: int, need: int, points: int, step: float, rate: float = 10.0, shift: float = 0.01, weight: Callable[[int], int] = lambda s: s, fit: DataFrame | None = None) -> DataFrame:
    """k, cdf by enumeration of compositions, as a plan (few compositions only; they are broadcast).  ``fit`` as above."""
    if comb(K + r, r) > ENUMERATE:
        raise ValueError("too many compositions; use cdf_messages with how='convolve'")
    rows = []
    for n in compositions(K, r + 1):
        if sum(weight(s) * c for s, c in enumerate(n)) >= need:
            ways = factorial(K)
            for c in n:
                ways //= factorial(c)
            rows.append((float(ways), list(n)))
    table = spark.createDataFrame(rows, "ways double, n array<int>")
    t = F.col("id") * step
    points_, rate, shift = _grid(spark, points, rate, shift, fit)

    def f(s: int):
        if s == 0:
            return F.lit(1.0)
        return F.lit(0.0) if s > r else F.when(t <= s * shift, 0.0).otherwise(1 - F.exp(-rate * (t / s - shift)))

    grid = points_.select(F.col("id").alias("k"), *[(f(s) - f(s + 1)).alias(f"p{s}") for s in range(r + 1)])
    term = F.col("ways")
    for s in range(r + 1):
        term = term * F.pow(f"p{s}", F.get("n", F.lit(s)))
    return grid.join(F.broadcast(table)).groupBy("k").agg(F.round(F.sum(term), 8).alias("cdf"))


def integrate(table: DataFrame, step: float) -> DataFrame:
    """One row: the trapezoid sum of 1 - cdf over a grid table (k, cdf)."""
    from pyspark.sql import Window

    before = F.lag("cdf").over(Window.orderBy("k"))  # a grid of some thousand points
    return table.withColumn("b", before).agg(F.round(F.sum((2 - F.col("cdf") - F.col("b")) / 2 * step), 6).alias("expected"))
