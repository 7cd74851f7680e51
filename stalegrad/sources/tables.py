"""Tables, traces and written layouts: sources and sinks of the engine."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed schemas; nothing is inferred from the files.
SCHEMAS = {
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "embeddings": "vec_id long, embedding array<float>, label int",
}

TRACE_SCHEMA = "worker int, t int, ts timestamp, comm_ms double, comp_ms double, round_trip_ms double"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A base table, with its fixed schema where one is declared."""
    reader = spark.read
    if name in SCHEMAS:
        reader = reader.schema(SCHEMAS[name])
    return reader.parquet(f"{sf_dir}/{name}.parquet")


def read_trace(spark: SparkSession, path: str, fmt: str = "csv") -> DataFrame:
    """Recorded latencies from CSV (with header) or JSON lines; malformed rows stop the read."""
    reader = spark.read.schema(TRACE_SCHEMA).option("mode", "FAILFAST")
    return reader.option("header", True).csv(path) if fmt == "csv" else reader.json(path)


def stream_trace(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Trace files of a folder as a stream."""
    return spark.readStream.schema(TRACE_SCHEMA).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def replicates(spark: SparkSession, count: int, slices: int | None = None) -> DataFrame:
    """Replicate ids 0..count-1, spread over tasks."""
    return spark.range(0, count, 1, slices or spark.sparkContext.defaultParallelism).withColumnRenamed("id", "replicate")


def write_layout(matrix: DataFrame, path: str, rows_per_file: int = 1_000_000) -> None:
    """The matrix sorted by ``sample_idx`` within one folder a worker.

    A subpartition is a row range, so the sorted files let a range predicate skip
    row groups, and changing the number of subpartitions never moves a row.
    """
    (
        matrix.repartitionByRange("worker", "sample_idx")
        .sortWithinPartitions("worker", "sample_idx")
        .write.option("maxRecordsPerFile", rows_per_file)
        .partitionBy("worker")
        .parquet(path)
    )


def rows_between(matrix: DataFrame, lo: int, hi: int) -> DataFrame:
    """Rows of one inclusive range; the predicate reaches the Parquet scan."""
    return matrix.where(F.col("sample_idx").between(lo, hi))


def shared_folder(spark: SparkSession) -> str:
    """The cluster's checkpoint folder; one under the warehouse where none is set."""
    context = spark.sparkContext._jsc.sc()
    if context.getCheckpointDir().isEmpty():
        base = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_stages"
        spark.sparkContext.setCheckpointDir(base)
    return context.getCheckpointDir().get()


def written(df: DataFrame, name: str = "stage") -> DataFrame:
    """``df`` written to the shared folder and read again: short lineage that survives lost executors."""
    path = f"{shared_folder(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def save_log(df: DataFrame, path: str) -> None:
    """Appends trajectory, delivery or cache rows."""
    df.write.mode("append").parquet(path)
