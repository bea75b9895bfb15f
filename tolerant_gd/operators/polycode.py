"""Gradient codes in exact arithmetic.

Batch k has the polynomial whose roots are the points of the codes that lack k; a code is
the gradients weighted by these polynomials at its point.  All polynomials are monic of one
degree h, so divided differences over any h + 1 codes give the sum of all gradients.
"""

from __future__ import annotations

from fractions import Fraction
from math import lcm, prod

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def supports(slots: list[tuple[int, int, int]], codes: list[tuple[int, int]] | None = None) -> list[set[int]]:
    """Batches of every code: of each worker, or of (worker, first ``m`` slots) pairs."""
    held: dict[int, list[int]] = {}
    for w, j, b in sorted(slots):
        held.setdefault(w, []).append(b)
    if codes is None:
        return [set(held[w]) for w in sorted(held)]
    return [set(held[w][:m]) for w, m in codes]


def degree(masks: list[set[int]], batches: set[int]) -> int:
    return max(sum(b not in m for m in masks) for b in batches)


def encode_coefs(masks: list[set[int]], points: list[int] | None = None, pad: bool = False) -> list[tuple[int, int, int]]:
    """(code, batch, coefficient).  With ``pad``, lighter columns get factors of unused points up to the common degree."""
    points = list(range(1, len(masks) + 1)) if points is None else points
    if len(set(points)) != len(masks):
        raise ValueError("points must be distinct, one a code")
    batches = set().union(*masks)
    h = degree(masks, batches)
    out = []
    for b in sorted(batches):
        zeros = [points[i] for i, m in enumerate(masks) if b not in m]
        if len(zeros) < h:
            if not pad:
                raise ValueError("columns differ in weight; pass pad=True")
            zeros += [-(1 + j) for j in range(h - len(zeros))]
        out += [(i, b, prod(points[i] - z for z in zeros)) for i, m in enumerate(masks) if b in m]
    return sorted(out)


def decode_coefs(points: list[int], received: list[int], h: int) -> tuple[list[tuple[int, int]], int]:
    """((code, integer weight), divisor): the sum of weight * code over the first h + 1 received is divisor * sum of gradients."""
    if len(received) < h + 1:
        raise ValueError(f"{h + 1} codes are needed, {len(received)} arrived")
    use = received[: h + 1]
    weights = [Fraction(1, prod(points[i] - points[j] for j in use if j != i)) for i in use]
    divisor = lcm(*[w.denominator for w in weights])
    return [(i, int(w * divisor)) for i, w in zip(use, weights, strict=True)], divisor


def roots_of_unity_coefs(masks: list[set[int]]) -> list[tuple[int, int, float, float]]:
    """The code at complex roots of unity, real and imaginary parts: best conditioned for floats."""
    import cmath

    points = [cmath.exp(2j * cmath.pi * i / len(masks)) for i in range(len(masks))]
    out = []
    for b in sorted(set().union(*masks)):
        zeros = [points[i] for i, m in enumerate(masks) if b not in m]
        for i, m in enumerate(masks):
            if b in m:
                c = prod((points[i] - z for z in zeros), start=complex(1))
                out.append((i, b, c.real, c.imag))
    return sorted(out)


def encode(grads: DataFrame, coefs: list[tuple[int, int, int]]) -> DataFrame:
    """code, dim, c: coded sums of (batch, dim, v); the coefficient table is broadcast (codes times load rows)."""
    table = grads.sparkSession.createDataFrame([(i, b, c) for i, b, c in coefs], "code int, batch int, c bigint")
    joined = grads.join(F.broadcast(table), "batch")
    return joined.groupBy("code", "dim").agg(F.sum((F.col("v") * F.col("c")).cast("decimal(38,0)")).alias("c"))


def decode(codes: DataFrame, sets: list[tuple[int, list[tuple[int, int]], int]]) -> DataFrame:
    """set_id, dim, v: the sum of all gradients, from each received set (id, integer weights, divisor)."""
    rows = [(s, i, w, d) for s, weights, d in sets for i, w in weights]
    table = codes.sparkSession.createDataFrame(rows, "set_id int, code int, w bigint, d bigint")
    summed = codes.join(F.broadcast(table), "code").groupBy("set_id", "dim", "d").agg(F.sum((F.col("c") * F.col("w")).cast("decimal(38,0)")).alias("v"))
    return summed.select("set_id", "dim", F.expr("v div d").cast("bigint").alias("v"))


def conditioning(masks: list[set[int]], received: list[int], points: list[int] | None = None) -> float:
    """Largest sum of absolute decode times encode weights of a batch: how much float error may grow."""
    points = list(range(1, len(masks) + 1)) if points is None else points
    h = degree(masks, set().union(*masks))
    weights, d = decode_coefs(points, received, h)
    by_code = dict(weights)
    total: dict[int, float] = {}
    for i, b, c in encode_coefs(masks, points):
        if i in by_code:
            total[b] = total.get(b, 0.0) + abs(by_code[i] * c / d)
    return max(total.values())


def growth(masks: list[set[int]], received: list[int], grads: dict[int, dict[int, int]], points: list[int] | None = None) -> float:
    """The same on given gradients (dim: batch: value): absolute decode times encode terms over the sum they leave, worst of all dims with a sum."""
    points = list(range(1, len(masks) + 1)) if points is None else points
    weights, d = decode_coefs(points, received, degree(masks, set().union(*masks)))
    by_code, amount = dict(weights), {}
    for i, b, c in encode_coefs(masks, points):
        if i in by_code:
            amount[b] = amount.get(b, 0.0) + abs(by_code[i] * c / d)
    return max((sum(a * abs(v.get(b, 0)) for b, a in amount.items()) / abs(sum(v.values())) for v in grads.values() if sum(v.values())), default=0.0)
