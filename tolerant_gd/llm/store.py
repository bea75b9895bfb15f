"""Intermediate tables in the folder that every executor shares."""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


_written: list[str] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder named in ``spark.checkpoint.dir``; where that is unset, a new one, on a single machine only."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        folder = "file://" + tempfile.mkdtemp(prefix="shared-")
        spark.conf.set("spark.checkpoint.dir", folder)
    return folder.rstrip("/")


def materialise(df: DataFrame, name: str, codec: str = "zstd") -> DataFrame:
    """Write ``df`` once and read it back: lineage ends at committed files that survive lost executors.

    The files stay as long as a result may need them; ``drop_written`` deletes them.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex[:12]}"
    df.write.option("compression", codec).parquet(path)
    _written.append(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_written(spark: SparkSession) -> int:
    """Delete all that ``materialise`` has written in this session, once its results are no longer read; how many tables."""
    jvm, conf, n = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration(), 0
    while _written:
        path = jvm.org.apache.hadoop.fs.Path(_written.pop())
        n += bool(path.getFileSystem(conf).delete(path, True))
    return n


def discard(*tables: DataFrame) -> None:
    """Delete tables of ``materialise`` that nothing reads any more."""
    for table in tables:
        spark, files = table.sparkSession, table.inputFiles()
        if files:
            path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(files[0].rsplit("/", 1)[0])
            path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
            _written[:] = [p for p in _written if p.rsplit("/", 1)[1] != path.getName()]


def release_shuffles(spark: SparkSession) -> None:
    """Let go of the shuffle files behind tables that are written: Spark deletes them only when the driver's JVM collects garbage, which may be after many stages."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def modest_batches(spark: SparkSession, most: int = 8_000_000) -> None:
    """Let Arrow batches to Python workers hold at most ``most`` bytes: a worker and its JVM hold several copies of one."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    now = (spark.conf.get(key, None) or "0").rstrip("b")
    if now.lstrip("-").isdigit() and not 0 < int(now) <= most:  # a size in other units is the user's own
        spark.conf.set(key, str(most))


def shuffle_width(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
