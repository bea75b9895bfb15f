"""Completion of rounds from live messages.

A round is a window of event time; a message is (round, worker, code).  ``completions``
keeps, per round, the set of codes seen and the count of messages, and emits one row the
moment enough are in; what comes after that is only counted.  ``tumbling``, ``sliding`` and
``session`` are the windowed loads around it.  Sources have NTZ timestamps, which watermarks
refuse, so the reader casts them in UTC.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import StructType

from tolerant_gd.sources.tables import SCHEMAS, shared_folder


def read_arrivals(spark: SparkSession, folder: str, round_length: int = 100, files_per_trigger: int = 1) -> DataFrame:
    """Streaming messages from a folder of event files: round = event_id div length, worker and code by modulo."""
    raw = spark.readStream.schema(StructType.fromDDL(SCHEMAS["events"])).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return as_messages(raw, round_length)


def as_messages(events: DataFrame, round_length: int = 100) -> DataFrame:
    return events.select(
        F.col("ts").cast("timestamp").alias("ts"),
        F.expr(f"event_id div {round_length}").alias("round"),
        F.pmod("user_id", F.lit(20)).cast("int").alias("worker"),
        F.pmod("event_id", F.lit(7)).cast("int").alias("step"),
        (F.pmod(F.col("user_id") + F.pmod("event_id", F.lit(7)), F.lit(20))).cast("int").alias("code"),
        F.col("event_id").alias("seq"),
    )


DONE = "round long, at timestamp, load long, codes long, distinct boolean"


def completions(messages: DataFrame, need: int, distinct: bool = True, delay: str = "1 day") -> DataFrame:
    """One row a round once ``need`` messages (or distinct codes) are in: when, and how many messages had come.

    State per round: a bit mask of codes, as many bytes as it needs, the count, and whether it has ended; it is dropped when the watermark passes.
    """

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        seen, count, ended = state.get if state.exists else (b"", 0, False)
        mask = int.from_bytes(seen, "little")
        out = []
        rows = pd.concat(list(batches)).sort_values(["ts", "seq"])
        for ts, code in zip(rows["ts"], rows["code"], strict=True):
            if ended:
                break
            mask, count = mask | 1 << int(code), count + 1
            have = mask.bit_count() if distinct else count
            if have >= need:
                ended = True
                out.append((key[0], ts, count, mask.bit_count(), distinct))
        state.update((mask.to_bytes(-(-mask.bit_length() // 8), "little"), count, ended))
        watermark = state.getCurrentWatermarkMs()
        last = int(rows["ts"].max().timestamp() * 1000)
        state.setTimeoutTimestamp(max(watermark, last) + 1)
        if out:
            yield pd.DataFrame(out, columns=["round", "at", "load", "codes", "distinct"])

    marked = messages.withWatermark("ts", delay)
    return marked.groupBy("round").applyInPandasWithState(step, DONE, "mask binary, count long, ended boolean", "append", GroupStateTimeout.EventTimeTimeout)


def tumbling(messages: DataFrame, length: str = "1 day", delay: str = "1 day") -> DataFrame:
    return messages.withWatermark("ts", delay).groupBy(F.window("ts", length)).agg(F.count("*").alias("load"), F.size(F.collect_set("code")).cast("bigint").alias("codes"))


def sliding(messages: DataFrame, length: str = "2 days", every: str = "1 day", delay: str = "1 day") -> DataFrame:
    return messages.withWatermark("ts", delay).groupBy(F.window("ts", length, every)).agg(F.count("*").alias("load"))


def session(messages: DataFrame, gap: str = "2 hours", delay: str = "1 day") -> DataFrame:
    return messages.withWatermark("ts", delay).groupBy(F.session_window("ts", gap), "worker").agg(F.count("*").alias("load"))


def first_copies(messages: DataFrame, delay: str = "1 day") -> DataFrame:
    """One message a code and round."""
    return messages.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["round", "code"])


def with_layout(messages: DataFrame, slots: DataFrame) -> DataFrame:
    """Stream-static join: the batches behind each message."""
    return messages.join(F.broadcast(slots), "worker")


def run_to_table(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Process all that is there, into a table in the shared folder; no row comes to the driver.

    Batches are written under their numbers, so that a repeated one counts once.  In complete mode each
    one is the whole result, and the last one stands.
    """
    spark = stream.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex[:12]}"
    numbers: list[int] = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/rows/batch={number}")
        numbers.append(number)

    query = stream.writeStream.foreachBatch(keep).option("checkpointLocation", f"{path}/state").outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    if not numbers:
        return spark.createDataFrame([], stream.schema)
    kept = numbers[-1:] if mode == "complete" else sorted(set(numbers))
    return spark.read.schema(stream.schema).parquet(*[f"{path}/rows/batch={n}" for n in kept])
