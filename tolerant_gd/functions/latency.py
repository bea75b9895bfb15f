"""Latency models as tables: trial, worker, unit (one computation), start (initial delay), in microseconds."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tolerant_gd.functions.randoms import portable, portable_int
from tolerant_gd.sources.tables import measurements


def grid(spark: SparkSession, trials: int, workers: int) -> DataFrame:
    return spark.range(trials).select(F.col("id").alias("trial"), F.explode(F.sequence(F.lit(0), F.lit(workers - 1))).alias("worker"))


def fitted_grid(spark: SparkSession, trials: int, fit: DataFrame) -> DataFrame:
    """Every trial with every row of ``fit`` (one a worker)."""
    return spark.range(trials).select(F.col("id").alias("trial")).crossJoin(F.broadcast(fit))


def exponential_us(u: Column, mean_us: Column | float) -> Column:
    """A draw of an exponential, to the microsecond; the logarithm is rounded before it is scaled, so engines agree."""
    return F.round(F.round(-F.log(u), 9) * mean_us).cast("bigint")


def shifted_exponential(spark: SparkSession, trials: int, workers: int, rate: float = 10.0, shift: float = 0.01, seed: int = 1, fit: DataFrame | None = None) -> DataFrame:
    """Shift plus an exponential of this rate (seconds), one draw a worker and trial for all its computations.

    Rows of ``fit`` (worker, shift, excess; microseconds) name the workers and give each its own two numbers instead.
    """
    if fit is None:
        keys, least, mean = grid(spark, trials, workers), F.lit(round(shift * 1e6)), 1e6 / rate
    else:
        keys, least, mean = fitted_grid(spark, trials, fit), F.col("shift"), F.col("excess")
    unit = least + exponential_us(portable(seed, F.col("trial"), F.col("worker")), mean)
    return keys.select("trial", "worker", unit.alias("unit"), F.lit(0).cast("bigint").alias("start"))


def _bootstrap(keys: DataFrame, measured: DataFrame, kind: str, pick: Column, name: str) -> DataFrame:
    """Attach a measurement of the worker by a hash index; the measurements are numbered, so this is an equi-join."""
    own = measured.where(F.col("kind") == kind).select("worker", "idx", F.col("us").alias(name))
    sizes = own.groupBy("worker").agg(F.count("*").alias("_n"))
    return keys.join(F.broadcast(sizes), "worker").withColumn("idx", F.pmod(pick, F.col("_n"))).join(own, ["worker", "idx"]).drop("idx", "_n")


def measured_units(spark: SparkSession, sf_dir: str, trials: int, workers: int = 20, seed: int = 1) -> DataFrame:
    """Computation times resampled from the worker's measurements, one draw a worker and trial."""
    keys = grid(spark, trials, workers)
    got = _bootstrap(keys, measurements(spark, sf_dir, workers), "comp", portable_int(seed, "u", F.col("trial"), F.col("worker")), "unit")
    return got.select("trial", "worker", "unit", F.lit(0).cast("bigint").alias("start"))


def measured_comm(spark: SparkSession, sf_dir: str, trials: int, steps: int, workers: int = 20, seed: int = 1, mean_us: int = 0) -> DataFrame:
    """trial, worker, step, x: a measured communication time per message, plus an exponential of mean ``mean_us``."""
    keys = grid(spark, trials, workers).withColumn("step", F.explode(F.sequence(F.lit(0), F.lit(steps - 1))))
    got = _bootstrap(keys, measurements(spark, sf_dir, workers), "comm", portable_int(seed, "c", F.col("trial"), F.col("worker"), F.col("step")), "x")
    if mean_us:
        got = got.withColumn("x", F.col("x") + exponential_us(portable(seed, "e", F.col("trial"), F.col("worker"), F.col("step")), float(mean_us)))
    return got.select("trial", "worker", "step", "x")


def initial_delay(lat: DataFrame, probability: Column | float, delay_us: Column | int, seed: int = 1) -> DataFrame:
    """With this probability a worker starts ``delay_us`` later in a round."""
    hit = portable(seed, "d", F.col("trial"), F.col("worker")) < (probability if isinstance(probability, Column) else F.lit(probability))
    late = delay_us if isinstance(delay_us, Column) else F.lit(delay_us)
    return lat.withColumn("start", F.col("start") + F.when(hit, late).otherwise(0).cast("bigint"))


def carry_over(residual: list[float], fresh: list[float], t: float) -> tuple[list[float], list[float]]:
    """(start times of this round, what is left of them after a round of length t)."""
    start = [a + b for a, b in zip(residual, fresh, strict=True)]
    return start, [max(0.0, s - t) for s in start]


def mean_shifted(rate: float, shift: float, s: int) -> float:
    return s * (shift + 1 / rate)


def cdf_shifted(rate: float, shift: float, s: int, t: float) -> float:
    """Probability that s computations are done by t."""
    return 0.0 if t <= s * shift else 1 - math.exp(-rate * (t / s - shift))
