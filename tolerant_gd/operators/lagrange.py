"""Lagrange-coded least squares, exact in the field of the prime 2**61 - 1, or in floats.

Blocks of rows are grouped, ``polys`` groups in all; each group has a polynomial through its
blocks at the points alpha.  A coded block is that polynomial at a point beta of its worker.
X~'(X~ theta), summed over the groups, is a polynomial of twice the degree; from enough of
its values its sum over the alphas is X'X theta.

Encoding keeps the K rows of one position together in one array, so only the source rows
are shuffled, and combines them in place.  Field elements are 64-bit integers multiplied by
limbs in vectors; coded rows go from encoder to worker without a shuffle.
"""

from __future__ import annotations

from collections.abc import Iterator
from decimal import Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tolerant_gd.functions import field
from tolerant_gd.functions.field import PRIME

FIELD = "decimal(38,0)"


class Code:
    """Points and coefficients of one Lagrange code, in the field or in floats."""

    def __init__(self, K: int, r: int, polys: int, exact: bool = True):
        if r % polys:
            raise ValueError("polys must divide r")
        self.K, self.r, self.polys, self.exact = K, r, polys, exact
        self.blocks = -(-K // polys)  # of a group, the last one padded with zero blocks
        self.draws = r // polys
        total = K * self.draws
        self.threshold = 2 * self.blocks - 1
        if total < self.threshold:
            raise ValueError(f"{total} messages can never reach the threshold {self.threshold}")
        if exact:
            self.alphas = list(range(1, self.blocks + 1))
            self.betas = list(range(self.blocks + 1, self.blocks + total + 1))
        else:
            from math import cos, pi

            points = [cos((2 * i + 1) * pi / (2 * (self.blocks + total))) for i in range(self.blocks + total)]
            self.alphas = points[:: (self.blocks + total) // self.blocks][: self.blocks]
            self.betas = [p for p in points if p not in set(self.alphas)][:total]
        if len({*self.alphas, *self.betas}) != self.blocks + total:
            raise ValueError("points must be distinct")

    def basis(self, nodes: list, z) -> list:
        """Lagrange basis polynomials of ``nodes`` at z."""
        out = []
        for i, a in enumerate(nodes):
            top, low = 1, 1
            for j, b in enumerate(nodes):
                if i != j:
                    top, low = top * (z - b), low * (a - b)
                    if self.exact:
                        top, low = top % PRIME, low % PRIME
            out.append(top * pow(low, -1, PRIME) % PRIME if self.exact else top / low)
        return out

    def encode_coefs(self) -> list[tuple[int, int, list]]:
        """(worker, draw, weights of the blocks of a group); the same for every group."""
        return [(w, u, self.basis(self.alphas, self.betas[w * self.draws + u])) for w in range(self.K) for u in range(self.draws)]

    def decode_coefs(self, received: list[int]) -> list[tuple[int, object]]:
        """(message, weight) over the first ``threshold`` received: the weighted sum of their values is the sum over alphas."""
        if len(received) < self.threshold:
            raise ValueError(f"{self.threshold} messages are needed, {len(received)} arrived")
        use = received[: self.threshold]
        nodes = [self.betas[i] for i in use]
        sums = [0] * len(use)
        if self.exact:  # all basis polynomials of one point share their product; what divides them is one inverse each
            low = [1] * len(use)
            for i, x in enumerate(nodes):
                for y in nodes:
                    if x != y:
                        low[i] = low[i] * (x - y) % PRIME
            for a in self.alphas:
                product = 1
                for x in nodes:
                    product = product * (a - x) % PRIME
                for i, x in enumerate(nodes):
                    sums[i] = (sums[i] + product * pow((a - x) * low[i], -1, PRIME)) % PRIME
        else:
            for a in self.alphas:
                sums = [t + v for t, v in zip(sums, self.basis(nodes, a), strict=True)]
        return list(zip(use, sums, strict=True))


def _mod(c: Column) -> Column:
    return F.pmod(c, F.lit(PRIME).cast(FIELD))


def encode(aligned: DataFrame, code: Code, xs: list[str], at_once: int = 2048) -> DataFrame:
    """message, grp, pos, x0..: coded rows (field elements) from aligned block rows (batch, pos, x0..).

    A position that a block lacks counts as a zero row, so padding rows may be left out.
    """
    group, slot = F.expr(f"batch div {code.blocks}"), (F.col("batch") % code.blocks).cast("int")
    cells = aligned.select(group.cast("int").alias("grp"), F.col("pos").cast("bigint").alias("pos"), F.struct(slot.alias("s"), *[F.col(x).cast("bigint").alias(x) for x in xs]).alias("c"))
    together = cells.groupBy("grp", "pos").agg(F.collect_list("c").alias("cs"))  # at most K / polys rows a position
    weights = [(w * code.draws + u, [int(c) for c in cs]) for w, u, cs in code.encode_coefs()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, at_once):
                grp, pos, cells = batch.slice(at, at_once).columns
                n, flat = len(grp), cells.flatten()
                row, block = np.repeat(np.arange(n), np.diff(cells.offsets.to_numpy())), flat.field("s").to_numpy()
                held = np.zeros((code.blocks, n, len(xs)), np.uint64)
                for i, x in enumerate(xs):
                    held[block, row, i] = field.elements(flat.field(x).to_numpy(zero_copy_only=False))
                for message, cs in weights:
                    coded = field.total(field.times(held, np.array(cs, np.uint64)[:, None, None])).view(np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(n, message, np.int32)), grp, pos, *[pa.array(coded[:, i]) for i in range(len(xs))]], ["message", "grp", "pos", *xs])

    return together.mapInArrow(run, "message int, grp int, pos bigint, " + ", ".join(f"{x} bigint" for x in xs))


def work(coded: DataFrame, theta: list[int], xs: list[str]) -> DataFrame:
    """message, dim, v: X~'(X~ theta) of every message, summed over its groups.

    Each task sums its own rows; what is shuffled is messages times features.
    """
    z = [np.uint64(int(t) % PRIME) for t in theta]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            if not batch.num_rows:
                continue
            sent = batch.column(0).to_numpy()
            x = np.stack([c.to_numpy().view(np.uint64) for c in batch.columns[1:]])
            inner = field.total(np.stack([field.times(v, np.broadcast_to(t, v.shape)) for v, t in zip(x, z, strict=True)]))
            each = field.times(x, np.broadcast_to(inner, x.shape))
            for message in np.unique(sent).tolist():
                mine = field.total(each[:, sent == message], axis=1)
                sums[message] = field.reduced(sums[message] + mine) if message in sums else mine
        rows = [(m, i, int(v)) for m, vs in sums.items() for i, v in enumerate(vs)]
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate((pa.int32(), pa.int32(), pa.int64()))], ["message", "dim", "v"])

    own = coded.select("message", *[F.col(x).cast("bigint").alias(x) for x in xs]).mapInArrow(run, "message int, dim int, v bigint")
    return own.groupBy("message", "dim").agg(_mod(F.sum(F.col("v").cast(FIELD)).cast(FIELD)).cast(FIELD).alias("v"))


def decode(values: DataFrame, code: Code, received: list[int]) -> DataFrame:
    """dim, v: X'X theta as a signed integer (it must be below half the prime)."""
    table = values.sparkSession.createDataFrame([(i, Decimal(int(w))) for i, w in code.decode_coefs(received)], "message int, w decimal(38,0)")
    terms = values.join(F.broadcast(table), "message").groupBy("dim").agg(F.sum(_mod((F.col("v") * F.col("w")).cast(FIELD)).cast(FIELD)).alias("s"))
    v = _mod(F.col("s").cast(FIELD))
    return terms.select("dim", F.when(v > PRIME // 2, v - F.lit(PRIME).cast(FIELD)).otherwise(v).cast("bigint").alias("v"))


def store(coded: DataFrame, path: str, draws: int) -> None:
    """Coded rows as Parquet by worker: reading the received workers alone prunes the others."""
    coded.withColumn("worker", F.expr(f"message div {draws}")).write.mode("overwrite").partitionBy("worker").parquet(path)


def float_residual(x, theta, K: int, r: int, polys: int, received: list[int]) -> float:
    """Relative error of decoding in floats, for one matrix held by the driver (conditioning study)."""
    code = Code(K, r, polys, exact=False)
    blocks = np.array_split(np.asarray(x, float), K)
    rows = max(len(b) for b in blocks)
    blocks = [np.pad(b, ((0, rows - len(b)), (0, 0))) for b in blocks] + [np.zeros((rows, len(theta)))] * (code.blocks * polys - K)
    values = []
    for _, _, w in code.encode_coefs():
        total = 0
        for q in range(polys):
            coded = sum(c * b for c, b in zip(w, blocks[q * code.blocks : (q + 1) * code.blocks], strict=True))
            total = total + coded.T @ (coded @ theta)
        values.append(total)
    got = sum(w * values[i] for i, w in code.decode_coefs(received))
    want = np.asarray(x, float).T @ (np.asarray(x, float) @ theta)
    return float(np.linalg.norm(got - want) / np.linalg.norm(want))


def cross_grams(aligned: DataFrame, xs: list[str], K: int):
    """Array (K, K, d, d) of X_b'X_c of all pairs of blocks, rows paired by ``pos``; exact integers.

    Every task sums its own positions; (K d)^2 numbers a task are shuffled and reach the driver as sums.
    """
    d = len(xs)

    def run(batches):
        total = np.zeros((K * d, K * d), np.int64)
        for batch in batches:
            m = np.zeros((batch.num_rows, K, d), np.int64)
            cells = batch.column(0)
            flat = cells.flatten()
            row = np.repeat(np.arange(batch.num_rows), np.diff(cells.offsets.to_numpy()))
            block = flat.field("batch").to_numpy()
            for i, x in enumerate(xs):
                m[row, block, i] = flat.field(x).to_numpy()
            wide = m.reshape(batch.num_rows, K * d)
            total += wide.T @ wide
        a, b = np.nonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.int32()), pa.array(b, pa.int32()), pa.array(total[a, b])], ["a", "b", "v"])

    cells = aligned.groupBy("pos").agg(F.collect_list(F.struct("batch", *[F.col(x).cast("bigint").alias(x) for x in xs])).alias("cs")).select("cs")
    out = np.zeros((K * d, K * d), np.int64)
    sums = cells.mapInArrow(run, "a int, b int, v bigint").groupBy("a", "b").agg(F.sum("v").alias("v")).toPandas()
    out[sums["a"], sums["b"]] = sums["v"]
    return out.reshape(K, d, K, d).transpose(0, 2, 1, 3)


def message_grams(grams, code: Code) -> list:
    """X~'X~ of every message, summed over its groups, from cross products of blocks; field elements, or floats."""
    pairs = [(b, c) for b in range(code.K) for c in range(code.K) if b // code.blocks == c // code.blocks]
    cells = np.stack([grams[b, c] for b, c in pairs])
    cells, out = field.elements(cells) if code.exact else cells.astype(float), []
    for _, _, w in code.encode_coefs():
        both = [w[b % code.blocks] * w[c % code.blocks] for b, c in pairs]
        if code.exact:
            each = np.array([v % PRIME for v in both], np.uint64)[:, None, None]
            out.append(field.total(field.times(cells, np.broadcast_to(each, cells.shape))))
        else:
            out.append(np.tensordot(np.array(both), cells, 1))
    return out


def decode_product(sent: np.ndarray, z: list[int], code: Code, received: list[int], weights: list | None = None) -> list[int]:
    """X'X z as signed integers (below half the prime) from values of the received messages alone.

    ``sent`` holds every message's matrix as field elements (``message_grams`` of an exact code, stacked).
    """
    held = sent if isinstance(sent, np.ndarray) else np.array(sent, np.uint64)
    weights = weights or code.decode_coefs(received)
    mine = held[[i for i, _ in weights]]
    point = np.array([int(t) % PRIME for t in z], np.uint64)
    values = field.total(field.times(mine, np.broadcast_to(point, mine.shape)), axis=2)  # what each message carries
    w = np.array([int(v) for _, v in weights], np.uint64)
    sums = field.total(field.times(values, np.broadcast_to(w[:, None], values.shape)))
    return [int(v) - PRIME if v > PRIME // 2 else int(v) for v in sums]


def gram_residual(grams, theta, code: Code, received: list[int]) -> float:
    """``float_residual`` of a table of any size, from its cross products."""
    theta = np.asarray(theta, float)
    sent = message_grams(grams, code)
    got = sum(w * (sent[i] @ theta) for i, w in code.decode_coefs(received))
    want = sum(np.asarray(grams[b, b], float) for b in range(code.K)) @ theta
    return float(np.linalg.norm(got - want) / np.linalg.norm(want))


def mds_gram(K: int, need: int, groups: int) -> list[list[int]]:
    """Vandermonde weights of ``K`` coded copies of ``need`` row groups of the Gram matrix; any ``need`` rows are invertible."""
    if groups != need:
        raise ValueError("as many row groups as rows needed")
    return [[pow(i + 1, j) for j in range(need)] for i in range(K)]


def mds_decode(K: int, need: int, received: list[int]) -> tuple[list[list[int]], int]:
    """Integer rows and divisor: rows[g] dotted with the received values is divisor * group g."""
    from fractions import Fraction
    from math import lcm

    m = [[Fraction(x) for x in mds_gram(K, need, need)[i]] + [Fraction(int(k == j)) for j in range(need)] for k, i in enumerate(received[:need])]
    for c in range(need):
        pivot = next(i for i in range(c, need) if m[i][c])
        m[c], m[pivot] = m[pivot], m[c]
        m[c] = [x / m[c][c] for x in m[c]]
        for i in range(need):
            if i != c and m[i][c]:
                m[i] = [a - m[i][c] * b for a, b in zip(m[i], m[c], strict=True)]
    inverse = [row[need:] for row in m]
    divisor = lcm(*[x.denominator for row in inverse for x in row])
    return [[int(x * divisor) for x in row] for row in inverse], divisor
