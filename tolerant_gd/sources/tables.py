"""Declared schemas, readers and sinks of the given tables."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "pages": "page_id bigint, url string, html string",
    "benchmark": "item_id bigint, text string",
    "labels": "doc_id bigint, quality int, toxic int",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table under its declared schema (nothing is inferred)."""
    return spark.read.schema(StructType.fromDDL(SCHEMAS[name])).parquet(f"{sf_dir}/{name}.parquet")


def read_files(spark: SparkSession, path: str, kind: str, schema: str, **options) -> DataFrame:
    """CSV, JSON, ORC or Parquet files under a declared schema."""
    return spark.read.format(kind).options(**options).schema(schema).load(path)


def write_files(df: DataFrame, path: str, kind: str = "parquet", by: list[str] | None = None, **options) -> None:
    """Write ``df``, partitioned by ``by``; an existing path is replaced."""
    writer = df.write.mode("overwrite").options(**options)
    (writer.partitionBy(*by) if by else writer).format(kind).save(path)


def shared_folder(spark: SparkSession) -> str:
    """The folder named in ``spark.checkpoint.dir``; where that is unset, a new one, on a single machine only."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        folder = "file://" + tempfile.mkdtemp(prefix="shared-")
        spark.conf.set("spark.checkpoint.dir", folder)
    return folder.rstrip("/")


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` once to the shared folder, and read it back: what follows sees one and the same table."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex[:12]}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def exact_sample(spark: SparkSession, sf_dir: str, K: int) -> DataFrame:
    """Integer regression data: batch, x0..x4 = 1, quantity, discount in %, tax in %, line number; y in cents."""
    li = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity", "l_discount", "l_tax", "l_linenumber", "l_extendedprice")

    def whole(c, by=1):
        return F.round(F.col(c) * by).cast("bigint")

    return li.select(
        "l_orderkey",
        F.pmod("l_orderkey", F.lit(K)).cast("int").alias("batch"),
        F.lit(1).cast("bigint").alias("x0"),
        whole("l_quantity").alias("x1"),
        whole("l_discount", 100).alias("x2"),
        whole("l_tax", 100).alias("x3"),
        F.col("l_linenumber").cast("bigint").alias("x4"),
        whole("l_extendedprice", 100).alias("y"),
    )


def vector_sample(spark: SparkSession, sf_dir: str, K: int, label_as_y: bool = True) -> DataFrame:
    """Embeddings as regression data: id, batch, x (array of double), y."""
    e = read(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("id"), F.pmod("vec_id", F.lit(K)).cast("int").alias("batch"), F.col("embedding").cast("array<double>").alias("x"), F.col("label").cast("double").alias("y"))


#: Ids of events that are ranked in one go.
ID_SLICE = 1 << 20


def measured_times(spark: SparkSession, sf_dir: str, workers: int = 20) -> DataFrame:
    """(worker, kind, event_id, us, user_id): events as measured computation and communication times."""
    e = read(spark, sf_dir, "events").select("event_id", "user_id", "event_type", "value")
    kind = F.when(F.col("event_type").isin("view", "click", "purchase"), "comp").otherwise("comm")
    us = F.when(kind == "comp", 500 + F.col("value") * 20).otherwise(F.col("value") * 10)
    return e.select(F.pmod("user_id", F.lit(workers)).cast("int").alias("worker"), kind.alias("kind"), "event_id", F.round(us).cast("bigint").alias("us"), "user_id")


def fitted_times(spark: SparkSession, sf_dir: str, by: list[str] | None = None, workers: int = 20) -> DataFrame:
    """(*by, shift, excess): the measured computation times as shifted exponentials, in whole microseconds: the least, and the mean beyond it.

    Workers are remainders with the sign of the user; events without a user are a worker (null) of their own.
    """
    comp = measured_times(spark, sf_dir, workers).withColumn("worker", (F.col("user_id") % workers).cast("int")).where("kind = 'comp'").groupBy(*(by or [])).agg(F.min("us").alias("shift"), F.sum("us").alias("s"), F.count("*").alias("n"))
    return comp.select(*(by or []), "shift", F.expr("s div n - shift").alias("excess"))


def measurements(spark: SparkSession, sf_dir: str, workers: int = 20) -> DataFrame:
    """(worker, kind, idx, us): the measured times, numbered per worker and kind."""
    from pyspark.sql import Window

    rows = measured_times(spark, sf_dir, workers)
    # ranks in two steps: inside slices of the ids, and rows of the slices before; no worker is one task
    rows = rows.withColumn("slice", F.expr(f"event_id div {ID_SLICE}"))
    own = F.row_number().over(Window.partitionBy("worker", "kind", "slice").orderBy("event_id")) - 1
    sizes = rows.groupBy("worker", "kind", "slice").agg(F.count("*").alias("n"))
    before = sizes.select("worker", "kind", "slice", (F.sum("n").over(Window.partitionBy("worker", "kind").orderBy("slice")) - F.col("n")).alias("before"))
    return rows.withColumn("own", own).join(before, ["worker", "kind", "slice"]).select("worker", "kind", (F.col("before") + F.col("own")).cast("bigint").alias("idx"), "us")
