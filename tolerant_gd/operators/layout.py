"""Layouts as tables: which worker holds which batches, in which order, and which codes it sends."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tolerant_gd.plans.scheme import Scheme, messages
from tolerant_gd.sources.tables import read


def _positions(spark: SparkSession, K: int, r: int) -> DataFrame:
    return spark.range(K).select(F.col("id").cast("int").alias("worker"), F.explode(F.sequence(F.lit(0), F.lit(r - 1))).alias("ord"))


def cyclic_layout(spark: SparkSession, K: int, r: int) -> DataFrame:
    """worker, ord, batch: worker i holds i .. i+r-1 modulo K, computed in that order."""
    return clustered_layout(spark, K, r, 1)


def clustered_layout(spark: SparkSession, K: int, r: int, P: int) -> DataFrame:
    """The cyclic layout inside each of P equal clusters of neighbouring workers."""
    if K % P or r > K // P:
        raise ValueError("P must divide K and clusters hold at least r workers")
    size = K // P
    batch = F.expr(f"worker div {size} * {size} + pmod(worker % {size} + ord, {size})")
    return _positions(spark, K, r).select("worker", "ord", batch.cast("int").alias("batch"))


def repetition_layout(spark: SparkSession, K: int, r: int) -> DataFrame:
    if K % r:
        raise ValueError("repetition needs r to divide K")
    return clustered_layout(spark, K, r, K // r)


def random_layout(spark: SparkSession, K: int, r: int, seed: int = 1) -> DataFrame:
    """r random batches a worker: the first by a hash of (seed, worker, batch)."""
    from tolerant_gd.functions.randoms import portable_int

    pairs = spark.range(K).select(F.col("id").cast("int").alias("worker"), F.explode(F.sequence(F.lit(0), F.lit(K - 1))).alias("batch"))
    rank = F.row_number().over(Window.partitionBy("worker").orderBy(portable_int(seed, F.col("worker"), F.col("batch")), "batch")) - 1
    return pairs.withColumn("ord", rank).where(F.col("ord") < r).select("worker", "ord", "batch")


def layered_layout(spark: SparkSession, K: int, orders: list[int], P: int = 1) -> DataFrame:
    """layer, worker, ord, batch: each layer is a virtual worker with the first slots of the real one."""
    slots = clustered_layout(spark, K, max(orders), P)
    layers = spark.createDataFrame([(a, m) for a, m in enumerate(orders)], "layer int, m int")
    return slots.join(F.broadcast(layers), F.col("ord") < F.col("m")).select("layer", "worker", "ord", "batch")


def shared_layout(spark: SparkSession, K: int, r: int, m: int, P: int = 1) -> DataFrame:
    """worker, step, code, needs: code k mixes batches k .. k+m-1; step q leaves after m+q computations."""
    return clustered_layout(spark, K, r - m + 1, P).select("worker", F.col("ord").alias("step"), F.col("batch").alias("code"), (F.col("ord") + m).alias("needs"))


def message_table(spark: SparkSession, schemes: list[Scheme]) -> DataFrame:
    """All messages of some schemes; at most workers times load rows each, so they may be broadcast."""
    from tolerant_gd.plans.scheme import message_threshold

    rows = [(i, s.label, m.worker, m.step, m.code, m.cluster, m.needs, int(m.full), int(m.first), message_threshold(s)) for i, s in enumerate(schemes) for m in messages(s)]
    return spark.createDataFrame(rows, "sid int, scheme string, worker int, step int, code int, cluster int, needs int, full int, first int, need int")


def mask_statistics(slots: DataFrame) -> DataFrame:
    """Per batch: copies; and over all: row sums and the degree a code on this mask needs (codes minus least copies)."""
    per_batch = slots.groupBy("batch").agg(F.count("*").alias("copies"), F.countDistinct("worker").alias("workers"))
    rows = slots.groupBy("worker").agg(F.count("*").alias("n"))
    span = rows.agg(F.min("n").alias("least_row"), F.max("n").alias("most_row"), F.count("*").alias("codes"))
    least = per_batch.agg(F.min("copies").alias("least_copies"))
    return per_batch.join(F.broadcast(span)).join(F.broadcast(least)).select("batch", "copies", "workers", "least_row", "most_row", (F.col("codes") - F.col("least_copies")).alias("degree"))


def region_clusters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """worker = nation, cluster = region: five clusters of five."""
    n, r = read(spark, sf_dir, "nation"), read(spark, sf_dir, "region")
    place = F.row_number().over(Window.partitionBy("r_regionkey").orderBy("n_nationkey")) - 1
    return n.join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").alias("worker"), F.dense_rank().over(Window.orderBy("r_regionkey")).alias("cluster"), place.alias("place"), "n_name", "r_name")
