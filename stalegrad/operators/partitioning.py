"""Row ranges, cyclic visits and the alignment of re-partitioned workers.

Everything is integer arithmetic on row numbers from 1: a worker owns a block of
rows, a block falls into subpartitions, and a new number of subpartitions is a
new predicate, never a move of rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def sub_bounds(rows: int, parts: int, k: int) -> tuple[int, int]:
    """First and last row of piece k of ``parts`` over rows 1..rows."""
    if not 1 <= parts <= rows:
        raise ValueError("between one piece and one piece a row")
    return (k - 1) * rows // parts + 1, k * rows // parts


def _whole(numerator: Column, denominator: Column) -> Column:
    """Integer division of non-negative numbers."""
    a, b = numerator.cast("long"), denominator.cast("long")
    return ((a - F.pmod(a, b)) / b).cast("long")


def sub_bounds_col(rows: Column, parts: Column, k: Column) -> tuple[Column, Column]:
    return (_whole((k - 1) * rows, parts).cast("long") + 1), _whole(k * rows, parts).cast("long")


def worker_layout(spark: SparkSession, n: int, workers: int) -> DataFrame:
    """(worker, first_row, last_row, rows): the even split of rows 1..n."""
    w = F.col("worker")
    lo, hi = sub_bounds_col(F.lit(n), F.lit(workers), w)
    return spark.range(1, workers + 1).select(F.col("id").cast("int").alias("worker")).select("worker", lo.alias("first_row"), hi.alias("last_row"), (hi - lo + 1).alias("rows"))


def pieces(layout: DataFrame, parts: Column | int) -> DataFrame:
    """Every subpartition of every worker with global row bounds."""
    p = F.lit(parts) if isinstance(parts, int) else parts
    split = layout.withColumn("parts", p.cast("int")).withColumn("k", F.explode(F.sequence(F.lit(1), F.col("parts"))))
    lo, hi = sub_bounds_col(F.col("rows"), F.col("parts"), F.col("k"))
    return split.select("worker", "parts", "k", (F.col("first_row") + lo - 1).alias("lo"), (F.col("first_row") + hi - 1).alias("hi"))


def assign(matrix: DataFrame, n: int, workers: int, parts: int) -> DataFrame:
    """Adds worker and k to rows with ``sample_idx``, in closed form (no join)."""
    i = F.col("sample_idx")
    worker = _whole(i * workers + n - 1, F.lit(n)).cast("int")  # the block that holds row i
    first = _whole((F.col("worker") - 1) * F.lit(n), F.lit(workers)).cast("long")
    last = _whole(F.col("worker") * F.lit(n), F.lit(workers)).cast("long")
    placed = matrix.withColumn("worker", worker)
    return placed.withColumn("k", _whole((i - first) * parts + (last - first) - 1, last - first).cast("int"))


def assign_by_layout(matrix: DataFrame, all_pieces: DataFrame) -> DataFrame:
    """The same for unequal piece counts: an equi join on the worker with a range condition."""
    bounds = all_pieces.select("worker", "k", "lo", "hi")
    return matrix.join(bounds, "worker").where(F.col("sample_idx").between(F.col("lo"), F.col("hi"))).drop("lo", "hi")


def next_sub(k: int, parts: int) -> int:
    return k % parts + 1


def translate(rows: int, old: int, new: int, k: int) -> int:
    """The new piece that holds the first row of old piece k."""
    start = sub_bounds(rows, old, k)[0]
    return (start * new + rows - 1) // rows


def align(rows: int, old: int, new: int, k: int, mode: str = "walk") -> int:
    """The piece to process when a task brings ``new`` pieces and piece k was the last one done.

    ``walk`` steps back until an old and a new piece start on the same row,
    ``nearest`` takes the latest aligned start not after the translated one,
    ``restart`` the first piece, ``none`` keeps the cyclic index.
    """
    k = next_sub(k, old)
    if mode == "restart":
        return 1
    if mode == "none":
        return min(k, new)
    j = translate(rows, old, new, k)
    if mode == "nearest":
        starts = {sub_bounds(rows, old, i)[0] for i in range(1, old + 1)}
        return next((i for i in range(j, 0, -1) if sub_bounds(rows, new, i)[0] in starts), 1)
    while sub_bounds(rows, old, k)[0] != sub_bounds(rows, new, j)[0]:
        j -= 1
        if j < 1:
            return 1
        k = translate(rows, new, old, j)
    return j


def translate_col(rows: Column, old: Column, new: Column, k: Column) -> Column:
    start = sub_bounds_col(rows, old, k)[0]
    return _whole(start * new + rows - 1, rows).cast("int")


def overlaps(cached: DataFrame, arriving: DataFrame) -> DataFrame:
    """Pairs of intervals of one worker that share a row; columns of the right side get ``new_``."""
    right = arriving.withColumnsRenamed({c: f"new_{c}" for c in arriving.columns if c != "worker"})
    return cached.join(right, "worker").where((F.col("lo") <= F.col("new_hi")) & (F.col("hi") >= F.col("new_lo")))
