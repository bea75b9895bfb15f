"""Every query of the engine, with SQL that states the same result."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from tolerant_gd.catalog import codes, completion, gradients, layouts, relational, streams, workloads

GROUPS = (gradients, layouts, codes, completion, workloads, streams, relational)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The gradient decoded from every sufficient set of coded messages."""
    return codes.QUERIES["decode_cyclic_all_sets"](spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for g in GROUPS for name, f in g.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for g in GROUPS for name, sql in g.ORACLES.items()}
