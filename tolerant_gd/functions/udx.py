"""Functions for SQL users: a scalar and an aggregate UDF on Arrow batches, and table functions for layouts and completion."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, LongType, StructType

from tolerant_gd.plans.scheme import message_threshold, messages, scheme


def _ints(*names: str) -> StructType:
    """Types as objects: reading DDL would need a running session at import."""
    out = StructType()
    for n in names:
        out = out.add(n, IntegerType())
    return out


@pandas_udf(ArrayType(DoubleType()))
def decode_weights(points: pd.Series) -> pd.Series:
    """Weights of received codes at the given points: inverse products of differences."""
    def one(p) -> list[float]:
        out = []
        for i, a in enumerate(p):
            w = 1.0
            for j, b in enumerate(p):
                if i != j:
                    w /= a - b
            out.append(w)
        return out

    return points.map(one)


@pandas_udf(LongType())
def nth_arrival(at: pd.Series, need: pd.Series) -> int:
    """The ``need``-th smallest arrival of a group (count recovery)."""
    n = int(need.iloc[0])
    return int(at.nsmallest(n).iloc[-1]) if len(at) >= n else -1


@udtf(returnType=_ints("worker", "ord", "batch"))
class CyclicLayout:
    """SELECT * FROM cyclic_layout(6, 3)"""

    def eval(self, K: int, r: int) -> Iterator[tuple[int, int, int]]:
        for w in range(K):
            for j in range(r):
                yield w, j, (w + j) % K


@udtf(returnType=_ints("worker", "step", "code", "needs", "need"))
class SchemeMessages:
    """SELECT * FROM scheme_messages('gradcode_shared', 6, 3, 2)"""

    def eval(self, name: str, K: int, r: int, order: int) -> Iterator[tuple[int, int, int, int, int]]:
        options = {"order": order} if name == "gradcode_shared" else {"polys": order} if name == "lagrange_multi" else {}
        s = scheme(name, K, r, **options)
        for m in messages(s):
            yield m.worker, m.step, m.code, m.needs, message_threshold(s)


@udtf(returnType=StructType().add("trial", IntegerType()).add("t", DoubleType()).add("load", IntegerType()))
class Completion:
    """SELECT * FROM completion('uncoded_multi', 40, 10, 1000): simulated rounds under the shifted exponential."""

    def eval(self, name: str, K: int, r: int, trials: int) -> Iterator[tuple[int, float, int]]:
        import numpy as np

        from tolerant_gd.functions.randoms import numpy_uniform
        from tolerant_gd.operators.simulate import Replay

        replay = Replay(scheme(name, K, r))
        unit = 0.01 - np.log(numpy_uniform(1, np.arange(trials)[:, None], np.arange(K)[None, :])) / 10
        t, load = replay.complete(replay.ready(unit, np.zeros_like(unit)))
        for i in range(trials):
            yield i, float(t[i]), int(load[i])


def register(spark: SparkSession) -> None:
    spark.udf.register("decode_weights", decode_weights)
    spark.udf.register("nth_arrival", nth_arrival)
    spark.udtf.register("cyclic_layout", CyclicLayout)
    spark.udtf.register("scheme_messages", SchemeMessages)
    spark.udtf.register("completion", Completion)
