"""Streaming queries over the events table, held against batch SQL of the same rounds."""

from __future__ import annotations

import itertools

from pyspark.sql import functions as F

from tolerant_gd.operators import layout
from tolerant_gd.streaming import detector

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
_number = itertools.count()

#: Messages in SQL.
MSG = "SELECT ts, event_id // 100 AS round, CAST(user_id % 20 AS INT) AS worker, CAST((user_id + event_id % 7) % 20 AS INT) AS code, event_id AS seq FROM events"


def _stream(s, d):
    # a glob of one file keeps the given table a streaming source without copying it
    return detector.read_arrivals(s, f"{d}/events.parquet*")


def _run(frame, mode="append"):
    return detector.run_to_table(frame, f"stream_result_{next(_number)}", mode)


def _completed(distinct: bool, need: int):
    def query(s, d):
        out = _run(detector.completions(_stream(s, d), need, distinct, "3650 days"))
        return out.select("round", "load", "codes", F.unix_micros("at").alias("at_us"))

    return query


def _completed_sql(distinct: bool, need: int) -> str:
    seen = f"SELECT *, count(*) OVER w AS load, bit_count(bit_or(1::BIGINT << code) OVER w) AS codes FROM ({MSG}) WINDOW w AS (PARTITION BY round ORDER BY ts, seq ROWS UNBOUNDED PRECEDING)"
    what = "codes" if distinct else "load"
    return f"SELECT round, load, CAST(codes AS BIGINT) AS codes, epoch_us(ts) AS at_us FROM (SELECT *, row_number() OVER (PARTITION BY round ORDER BY seq) AS n FROM ({seen}) WHERE {what} >= {need}) WHERE n = 1"


QUERIES["stream_rounds_count"] = _completed(False, 39)
ORACLES["stream_rounds_count"] = _completed_sql(False, 39)
QUERIES["stream_rounds_distinct"] = _completed(True, 18)
ORACLES["stream_rounds_distinct"] = _completed_sql(True, 18)
QUERIES["stream_tumbling"] = lambda s, d: _run(detector.tumbling(_stream(s, d)), "complete").select(F.unix_micros(F.col("window.start")).alias("start_us"), "load", "codes")
ORACLES["stream_tumbling"] = f"SELECT epoch_us(date_trunc('day', ts)) AS start_us, count(*) AS load, CAST(bit_count(bit_or(1::BIGINT << code)) AS BIGINT) AS codes FROM ({MSG}) GROUP BY 1"
QUERIES["stream_sliding"] = lambda s, d: _run(detector.sliding(_stream(s, d)), "complete").select(F.unix_micros(F.col("window.start")).alias("start_us"), "load")
ORACLES["stream_sliding"] = f"SELECT epoch_us(date_trunc('day', ts) - to_days(CAST(o AS INT))) AS start_us, count(*) AS load FROM ({MSG}), generate_series(0, 1) t(o) GROUP BY 1"
QUERIES["stream_session"] = lambda s, d: _run(detector.session(_stream(s, d)), "complete").groupBy("worker").agg(F.count("*").alias("sessions"), F.sum("load").alias("load"))
ORACLES["stream_session"] = f"SELECT worker, CAST(sum(new) AS BIGINT) AS sessions, count(*) AS load FROM (SELECT worker, CASE WHEN ts - lag(ts) OVER (PARTITION BY worker ORDER BY ts) < INTERVAL 2 HOURS THEN 0 ELSE 1 END AS new FROM ({MSG})) GROUP BY worker"
QUERIES["stream_dedup"] = lambda s, d: _run(detector.first_copies(_stream(s, d), "3650 days")).groupBy("round").agg(F.count("*").alias("codes"))
ORACLES["stream_dedup"] = f"SELECT round, count(DISTINCT code) AS codes FROM ({MSG}) GROUP BY round"
QUERIES["stream_static_join"] = lambda s, d: _run(detector.with_layout(_stream(s, d), layout.cyclic_layout(s, 20, 3)).where("ord = step % 3").select("round", "batch")).groupBy("batch").agg(F.count("*").alias("n"))
ORACLES["stream_static_join"] = f"SELECT CAST((worker + (seq % 7) % 3) % 20 AS INT) AS batch, count(*) AS n FROM ({MSG}) GROUP BY 1"


def _late(s, d):
    """Messages that came after their round had ended: counted by replaying the completions against the messages."""
    ends = _run(detector.completions(_stream(s, d), 18, True, "3650 days"))
    msgs = detector.as_messages(s.read.parquet(f"{d}/events.parquet"))
    return msgs.join(ends.select("round", "at"), "round").groupBy("round").agg(F.count(F.when(F.col("ts") > F.col("at"), 1)).alias("late"))


QUERIES["stream_late"] = _late
ORACLES["stream_late"] = f"WITH e AS ({_completed_sql(True, 18)}) SELECT round, count(*) FILTER (epoch_us(ts) > at_us) AS late FROM ({MSG}) JOIN e USING (round) GROUP BY round"


def _for_each(s, d):
    """Arrivals counted batch by batch, by batch number, so that a repeated batch counts once: no message is lost or doubled."""
    counts: dict[int, int] = {}

    def keep(batch, number):
        counts[number] = batch.count()

    q = _stream(s, d).writeStream.foreachBatch(keep).trigger(availableNow=True).start()
    q.awaitTermination()
    return s.createDataFrame([(sum(counts.values()),)], "messages long")


QUERIES["stream_foreach_batch"] = _for_each
ORACLES["stream_foreach_batch"] = "SELECT count(*) AS messages FROM events"
