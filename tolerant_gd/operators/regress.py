"""The gradient substrate: losses, full and partial gradients, Gram form, splits, padding.

Wide integer samples have columns x0..x{d-1}, y and batch (exact sums); vector samples have
x (array of double), y and batch.  Every operator is one scan with partial aggregation: what
is shuffled is d or K times d numbers a task, never rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tolerant_gd.sources.tables import materialise

EXACT = "decimal(38,0)"


def features(df: DataFrame) -> list[str]:
    return sorted((c for c in df.columns if c[0] == "x" and c[1:].isdigit()), key=lambda c: int(c[1:]))


def _linear(xs: list[str], theta) -> Column:
    total = F.lit(0)
    for x, t in zip(xs, theta, strict=True):
        total = total + F.col(x) * F.lit(t)
    return total


def dot(x: Column, theta) -> Column:
    """Inner product of an array column with constants."""
    return F.aggregate(F.zip_with(x, F.array(*[F.lit(float(t)) for t in theta]), lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b)


def loss(df: DataFrame, theta, kind: str = "squared", normalise: bool = True) -> DataFrame:
    """One row: loss.  squared: sum of squares / 2; logistic: log(1 + exp(-y z)) with y in {0, 1} read as {-1, 1}."""
    z = _linear(features(df), theta) if features(df) else dot(F.col("x"), theta)
    if kind == "squared":
        each = (z - F.col("y")) * (z - F.col("y")) / 2
    elif kind == "logistic":
        each = F.log1p(F.exp(-(2 * F.col("y") - 1) * z))
    else:
        raise ValueError(f"unknown loss {kind}")
    return df.agg((F.avg(each) if normalise else F.sum(each)).alias("loss"))


def _pull(df: DataFrame, theta, kind: str) -> Column:
    """Derivative of the loss in the linear form."""
    z = _linear(features(df), theta) if features(df) else dot(F.col("x"), theta)
    if kind == "squared":
        return z - F.col("y")
    if kind == "logistic":
        return 1 / (1 + F.exp(-z)) - F.col("y")
    raise ValueError(f"unknown loss {kind}")


def _long(wide: DataFrame, keys: list[str], d: int) -> DataFrame:
    pairs = F.explode(F.array(*[F.struct(F.lit(i).alias("dim"), F.col(f"g{i}").alias("v")) for i in range(d)]))
    return wide.select(*keys, pairs.alias("p")).select(*keys, "p.dim", "p.v")


def partial_gradients(df: DataFrame, theta, kind: str = "squared", by: str = "batch") -> DataFrame:
    """batch, dim, v: unscaled sums, and n (rows), so that means are formed at the end."""
    xs = features(df)
    if xs:
        pull = df.withColumn("_r", _pull(df, theta, kind))
        exact = kind == "squared"
        sums = [F.sum(F.col("_r") * F.col(x) if not exact else (F.col("_r") * F.col(x)).cast(EXACT)).alias(f"g{i}") for i, x in enumerate(xs)]
        return _long(pull.groupBy(by).agg(*sums), [by], len(xs))
    d = len(theta)
    pull = df.select(by, "x", _pull(df, theta, kind).alias("_r"))
    wide = pull.groupBy(by).agg(*[F.sum(F.get("x", F.lit(i)) * F.col("_r")).alias(f"g{i}") for i in range(d)])
    return _long(wide, [by], d)


def batch_sizes(df: DataFrame) -> DataFrame:
    return df.groupBy("batch").agg(F.count("*").alias("n"))


def full_gradient(df: DataFrame, theta, kind: str = "squared", normalise: bool = False) -> DataFrame:
    """dim, v: the gradient over all rows."""
    one = partial_gradients(df.withColumn("_all", F.lit(0)), theta, kind, by="_all").select("dim", "v")
    if not normalise:
        return one
    return one.join(F.broadcast(df.agg(F.count("*").alias("n")))).select("dim", (F.col("v").cast("double") / F.col("n")).alias("v"))


def gram(df: DataFrame) -> DataFrame:
    """i, j, v with i <= j: the upper half of X'X; and rows with j = -1: X'y.  One scan; constant over rounds."""
    xs = features(df)
    exact = bool(xs)
    d = len(xs) if xs else None
    if d is None:
        raise ValueError("use gram_vectors for array samples")
    pairs = [(i, j) for i in range(d) for j in range(i, d)]
    sums = [F.sum((F.col(xs[i]) * F.col(xs[j])).cast(EXACT) if exact else F.col(xs[i]) * F.col(xs[j])).alias(f"w{i}_{j}") for i, j in pairs]
    sums += [F.sum((F.col(xs[i]) * F.col("y")).cast(EXACT)).alias(f"b{i}") for i in range(d)]
    wide = df.agg(*sums)
    cells = [F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.col(f"w{i}_{j}").alias("v")) for i, j in pairs]
    cells += [F.struct(F.lit(i).alias("i"), F.lit(-1).alias("j"), F.col(f"b{i}").alias("v")) for i in range(d)]
    return wide.select(F.explode(F.array(*cells)).alias("c")).select("c.*")


def gram_vectors(df: DataFrame, d: int, by: str = "batch") -> DataFrame:
    """by, i, j, v for array samples (j = -1: X'y, i = j = -1: y'y, i = -1, j = -2: rows): sums per task in matrix form, then one small shuffle.

    d (d + 3) / 2 + 2 numbers a task and group are shuffled; beyond some dozen features this beats one expression a cell.
    """
    from collections.abc import Iterator

    import numpy as np
    import pyarrow as pa

    upper = np.triu_indices(d)
    rows = np.concatenate([upper[0], np.arange(d), [-1, -1]])
    columns = np.concatenate([upper[1], np.full(d, -1), [-1, -2]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        for batch in batches:
            x = batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
            y, g = batch.column(2).to_numpy(zero_copy_only=False), batch.column(0).to_numpy(zero_copy_only=False)
            for k in np.unique(g):
                m = g == k
                part = np.concatenate([(x[m].T @ x[m])[upper], x[m].T @ y[m], [y[m] @ y[m], m.sum()]])
                held[int(k)] = held[int(k)] + part if int(k) in held else part
        for k, v in held.items():
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(v), k, np.int64)), pa.array(rows.astype(np.int32)), pa.array(columns.astype(np.int32)), pa.array(v)], [by, "i", "j", "v"])

    parts = df.select(F.col(by).cast("long"), "x", F.col("y").cast("double")).mapInArrow(run, f"{by} long, i int, j int, v double")
    return parts.groupBy(by, "i", "j").agg(F.sum("v").alias("v"))


def gram_gradient(g: DataFrame, theta) -> DataFrame:
    """dim, v: X'X theta - X'y from the Gram form; no scan of the sample."""
    weights = F.array(*[F.lit(t) for t in theta])
    full = g.where("j >= 0").select("i", "j", "v").union(g.where("j > i").select(F.col("j").alias("i"), F.col("i").alias("j"), "v"))
    left = full.select(F.col("i").alias("dim"), (F.col("v") * F.get(weights, F.col("j"))).alias("v"))
    right = g.where("j = -1").select(F.col("i").alias("dim"), (-F.col("v")).alias("v"))
    return left.union(right).groupBy("dim").agg(F.sum("v").alias("v"))


def block_products(df: DataFrame, theta) -> DataFrame:
    """batch, dim, v: X_k'X_k theta of every block, whose sum is X'X theta."""
    return partial_gradients(df.withColumn("y", F.lit(0).cast("bigint")), theta)


def _dealt(df: DataFrame, key: list[str]) -> DataFrame:
    """``df`` in range partitions of ``key`` numbered by ``_part``.

    Range borders come from a sample, so the dealt table is written once: counts and ranks must see the same borders.
    """
    parts = max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return materialise(df.repartitionByRange(parts, *key).withColumn("_part", F.spark_partition_id()), "dealt")


def split_balanced(df: DataFrame, K: int, key: list[str]) -> DataFrame:
    """Add ``batch``: contiguous runs in key order whose sizes differ by one at most.

    Ranks come in two steps, a count per range partition and a rank inside it, so no task sees all rows.
    """
    dealt = _dealt(df, key)
    sizes = dealt.groupBy("_part").agg(F.count("*").alias("_n"))
    before = sizes.select("_part", (F.sum("_n").over(Window.orderBy("_part")) - F.col("_n")).alias("_before"), F.sum("_n").over(Window.partitionBy(F.lit(0))).alias("_all"))
    own = F.row_number().over(Window.partitionBy("_part").orderBy(*key)) - 1
    ranked = dealt.withColumn("_own", own).join(F.broadcast(before), "_part").withColumn("_rank", F.col("_before") + F.col("_own"))
    small, more = F.expr(f"_all div {K}"), F.expr(f"_all % {K}")
    edge = (small + 1) * more
    batch = F.when(F.col("_rank") < edge, F.floor(F.col("_rank") / (small + 1))).otherwise(more + F.floor((F.col("_rank") - edge) / F.greatest(small, F.lit(1))))
    return ranked.withColumn("batch", batch.cast("int")).drop("_part", "_own", "_before", "_all", "_rank")


def align_blocks(df: DataFrame, order: list[str]) -> DataFrame:
    """Add ``pos``: the rank of a row in its batch, in two steps like ``split_balanced``; a batch is never one task."""
    dealt = _dealt(df, ["batch", *order])
    sizes = dealt.groupBy("batch", "_part").agg(F.count("*").alias("_n"))
    before = sizes.select("batch", "_part", (F.sum("_n").over(Window.partitionBy("batch").orderBy("_part")) - F.col("_n")).alias("_before"))
    own = F.row_number().over(Window.partitionBy("_part", "batch").orderBy(*order)) - 1
    return dealt.withColumn("_own", own).join(F.broadcast(before), ["batch", "_part"]).withColumn("pos", F.col("_before") + F.col("_own")).drop("_part", "_own", "_before")


def pad_blocks(df: DataFrame, order: list[str], run: int = 100_000) -> DataFrame:
    """Rows of every batch aligned by ``pos``; shorter batches are filled with zero rows, made in runs of ``run``."""
    xs = features(df)
    ranked = align_blocks(df, order).select("batch", "pos", *xs, "y")
    sizes = ranked.groupBy("batch").agg(F.max("pos").alias("m"))
    lacking = sizes.join(F.broadcast(sizes.agg(F.max("m").alias("top")))).where("m < top")
    runs = lacking.select("batch", "top", F.explode(F.sequence(F.col("m") + 1, F.col("top"), F.lit(run).cast("bigint"))).alias("at")).repartition("batch", "at")
    zeros = runs.select("batch", F.explode(F.sequence("at", F.least(F.col("at") + (run - 1), "top"))).alias("pos"))
    kinds = dict(df.dtypes)
    return ranked.unionByName(zeros.select("batch", "pos", *[F.lit(0).cast(kinds[c]).alias(c) for c in (*xs, "y")]))
