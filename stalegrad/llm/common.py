"""Helpers shared by the text operators: written stages, ranks and prefix sums."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Words are split at these characters only (space, tab to carriage return).
WORD_BREAKS = r"[\x20\x09-\x0D]+"


def shared_folder(spark: SparkSession) -> str:
    """The cluster's checkpoint folder; one under the warehouse where none is set."""
    context = spark.sparkContext._jsc.sc()
    if context.getCheckpointDir().isEmpty():
        base = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_stages"
        spark.sparkContext.setCheckpointDir(base)
    return context.getCheckpointDir().get()


def written(df: DataFrame, name: str = "stage") -> DataFrame:
    """``df`` as a Parquet table in the shared folder: cuts the lineage, survives lost executors.

    Preferred to ``checkpoint()``, which computes the last stage twice and keeps
    rows uncompressed.
    """
    spark = df.sparkSession
    path = f"{_stages(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def _stages(spark: SparkSession) -> str:
    return f"{shared_folder(spark)}/stages-{spark.sparkContext.applicationId}"


def clear_stages(spark: SparkSession) -> None:
    """Removes what ``written`` has left for this application; call it once the results are stored elsewhere."""
    context = spark.sparkContext
    path = context._jvm.org.apache.hadoop.fs.Path(_stages(spark))
    path.getFileSystem(context._jsc.hadoopConfiguration()).delete(path, True)


def fresh(df: DataFrame, name: str) -> str:
    """A column name near ``name`` that ``df`` does not have."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = "_" + name
    return name


def running_totals(df: DataFrame, key: str, values: list[str], groups: list[str] = (), block: int = 4096, descending: bool = False) -> DataFrame:
    """Inclusive running sums of ``values`` along integer ``key`` within ``groups``.

    Two levels: sums by block of keys, offsets over the blocks, then a window
    inside each block, so no task sees more than one block of keys or the list
    of blocks.  ``key`` is unique within its group.
    """
    groups = list(groups)
    sign = -1 if descending else 1
    tagged = df.withColumn("_block", F.floor(F.col(key) / block) * sign)
    totals = tagged.groupBy(*groups, "_block").agg(*[F.sum(v).alias(f"_t_{v}") for v in values])
    before = Window.partitionBy(*groups or [F.lit(0)]).orderBy("_block").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select(*groups, "_block", *[F.coalesce(F.sum(f"_t_{v}").over(before), F.lit(0)).alias(f"_o_{v}") for v in values])
    inside = Window.partitionBy(*groups, "_block").orderBy(F.col(key) * sign).rowsBetween(Window.unboundedPreceding, 0)
    out = tagged.select("*", *[F.sum(v).over(inside).alias(f"_r_{v}") for v in values]).join(offsets, [*groups, "_block"])
    return out.select(*df.columns, *[(F.col(f"_r_{v}") + F.col(f"_o_{v}")).cast("long").alias(f"run_{v}") for v in values])


def ranked(df: DataFrame, groups: list[str], order: list[Column], spread: Column, buckets: int, name: str = "rank") -> DataFrame:
    """Rank from 0 within ``groups`` along (spread bucket, order), however large a group is.

    ``spread`` is a double in [0, 1) that grows with the wanted order; rows are
    dealt by (group, bucket of spread), bucket counts give the offsets.  The
    group columns must not be null.
    """
    bucketed = df.withColumn("_bucket", F.least(F.floor(spread * buckets), F.lit(buckets - 1)))
    counts = bucketed.groupBy(*groups, "_bucket").agg(F.count(F.lit(1)).alias("_n"))
    offsets = running_totals(counts, "_bucket", ["_n"], groups).select(*groups, "_bucket", (F.col("run__n") - F.col("_n")).alias("_before"))
    inside = Window.partitionBy(*groups, "_bucket").orderBy(*order)
    return bucketed.withColumn("_at", F.row_number().over(inside) - 1).join(offsets, [*groups, "_bucket"]).withColumn(name, (F.col("_before") + F.col("_at")).cast("long")).drop("_bucket", "_at", "_before")


def unit_hash(*cols: Column | str, seed: int = 0) -> Column:
    """A double in [0, 1) from a 64-bit hash (the top 52 bits)."""
    return F.shiftrightunsigned(F.xxhash64(F.lit(seed), *cols), 12) / F.lit(float(1 << 52))
