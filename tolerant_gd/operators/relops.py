"""Relational operators that the engine's users need around the methods."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def broadcast_if_small(df: DataFrame, rows: int = 1_000_000) -> DataFrame:
    """Hint a broadcast only after counting; larger sides are left to shuffled joins."""
    return F.broadcast(df) if df.count() <= rows else df


def salted_join(left: DataFrame, right: DataFrame, key: str, spread: Column, salts: int = 16) -> DataFrame:
    """Inner join that deals each key of the left side over ``salts`` groups; the right side is repeated that often."""
    a = left.withColumn("_salt", F.pmod(F.xxhash64(spread), F.lit(salts)))
    b = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)).cast("array<bigint>")))
    return a.join(b, [key, "_salt"]).drop("_salt")


def as_of(left: DataFrame, right: DataFrame, by: str, at: str, value: str) -> DataFrame:
    """Last ``value`` of ``right`` at or before each row of ``left``: one shuffle, no pairs.

    Both sides are laid on one line of time; a running last-non-null value answers every left row.
    """
    a = left.withColumn("_side", F.lit(1)).withColumn("_value", F.lit(None).cast(dict(right.dtypes)[value]))
    b = right.select(by, at, F.lit(0).alias("_side"), F.col(value).alias("_value"))
    order = Window.partitionBy(by).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b, allowMissingColumns=True)
    return both.withColumn(f"last_{value}", F.last("_value", ignorenulls=True).over(order)).where("_side = 1").drop("_side", "_value")


def range_join(points: DataFrame, ranges: DataFrame, at: str, low: str, high: str, width: int) -> DataFrame:
    """Points within [low, high): both sides meet in buckets of ``width``, so this is an equi-join with a residual filter."""
    a = points.withColumn("_bucket", F.floor(F.col(at) / width))
    b = ranges.withColumn("_bucket", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor((F.col(high) - 1) / width))))
    return a.join(b, "_bucket").where((F.col(at) >= F.col(low)) & (F.col(at) < F.col(high))).drop("_bucket")


def top_per_group(df: DataFrame, by: list[str], order: list[Column], n: int) -> DataFrame:
    return df.withColumn("_n", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("_n") <= n).drop("_n")
