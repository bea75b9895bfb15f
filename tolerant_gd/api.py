"""The engine in one import: schemes, layouts, codes, latency, recovery, statistics, training, streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tolerant_gd.functions import latency as _latency
from tolerant_gd.operators import lagrange as _lagrange
from tolerant_gd.operators import layout as _layout
from tolerant_gd.operators import polycode as _polycode
from tolerant_gd.operators.analytic import cdf, cdf_messages, cdf_workers, expected_completion, expected_workers
from tolerant_gd.operators.recover import arrivals, complete, congested, first_copies, missing_batches, reductions, summarise, traffic_bytes, waste
from tolerant_gd.operators.regress import full_gradient, gram, gram_gradient, loss, pad_blocks, partial_gradients, split_balanced
from tolerant_gd.operators.simulate import rounds, sweep, trials
from tolerant_gd.operators.train import coded_descend, descend, partial_error, train
from tolerant_gd.plans.scheme import Scheme, advise, decode_ops, expansion, feasible, message_threshold, recoverable, scheme, slots, worker_threshold
from tolerant_gd.streaming.detector import completions as detect_stream
from tolerant_gd.streaming.detector import read_arrivals

__all__ = [
    "Scheme", "advise", "arrivals", "cdf", "cdf_messages", "cdf_workers", "coded_descend", "complete", "congested", "decode", "decode_ops", "descend", "detect_stream", "encode",
    "expansion", "expected_completion", "expected_workers", "feasible", "first_copies", "full_gradient", "gram", "gram_gradient", "lagrange_encode", "latency", "layout", "loss",
    "message_threshold", "messages", "missing_batches", "pad_blocks", "partial_error", "partial_gradients", "read_arrivals", "recoverable", "reductions", "rounds", "scheme", "split_balanced",
    "summarise", "sweep", "traffic_bytes", "train", "trials", "waste", "worker_threshold",
]


def layout(spark: SparkSession, s: Scheme) -> DataFrame:
    """worker, ord, batch: what each worker holds, in the order in which it computes."""
    if s.name == "backup_workers":
        return spark.createDataFrame(slots(s), "worker int, ord int, batch int")
    return _layout.clustered_layout(spark, s.K, s.r, s.P)


def messages(spark: SparkSession, s: Scheme) -> DataFrame:
    """worker, step, code, cluster, needs, full, first, need of every message."""
    return _layout.message_table(spark, [s])


def _masks(s: Scheme) -> list[set[int]]:
    if s.P != 1 or not s.name.startswith("gradcode"):
        raise ValueError("encode one cluster of a gradient code at a time")
    if s.name in ("gradcode_layered", "gradcode_hybrid"):
        return _polycode.supports(slots(s), [(w, m) for w in range(s.K) for m in sorted(s.orders)])
    m = s.order if s.name == "gradcode_shared" else s.r
    return [{(k + j) % s.K for j in range(m)} for k in range(s.K)]


def encode(grads: DataFrame, s: Scheme) -> DataFrame:
    """code, dim, c of partial gradients (batch, dim, v)."""
    return _polycode.encode(grads, _polycode.encode_coefs(_masks(s)))


def decode(codes: DataFrame, received: list[int], s: Scheme) -> DataFrame:
    """dim, v: the sum of all gradients from the received codes, in order of arrival."""
    masks = _masks(s)
    weights, divisor = _polycode.decode_coefs(list(range(1, len(masks) + 1)), received, _polycode.degree(masks, set().union(*masks)))
    return _polycode.decode(codes, [(0, weights, divisor)]).select("dim", "v")


def lagrange_encode(aligned: DataFrame, s: Scheme, features: list[str], source_bytes: int = 0, allow_expand: bool = False) -> DataFrame:
    """message, grp, pos, features of aligned block rows; stores r coded copies, so it must be allowed."""
    expansion(s, source_bytes, allow_expand)
    return _lagrange.encode(aligned, _lagrange.Code(s.K, s.r, s.polys if s.name == "lagrange_multi" else s.r), features)


def latency(spark: SparkSession, model: str, n: int, workers: int, sf_dir: str = "", **options) -> DataFrame:
    """trial, worker, unit, start by name: ``shifted_exponential`` or ``measured``."""
    if model == "shifted_exponential":
        return _latency.shifted_exponential(spark, n, workers, **options)
    if model == "measured":
        return _latency.measured_units(spark, sf_dir, n, workers, **options)
    raise ValueError(f"unknown latency model {model}")
