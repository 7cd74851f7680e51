"""Cost and accuracy measures over trajectories, delivery logs and cache events."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def time_to_gap(trajectory: DataFrame, levels: list[float], by: list[str] = ("method",)) -> DataFrame:
    """First virtual time at which the gap is at most each level (null if never)."""
    per = trajectory.withColumn("eps", F.explode(F.array(*[F.lit(float(e)) for e in levels])))
    return per.groupBy(*by, "eps").agg(F.min(F.when(F.col("gap") <= F.col("eps"), F.col("time_ms"))).alias("time_ms"))


def speedup(times: DataFrame, a: str, b: str) -> DataFrame:
    """Time of method b over that of method a at each level."""
    left = times.where(F.col("method") == a).select("eps", F.col("time_ms").alias("_a"))
    right = times.where(F.col("method") == b).select("eps", F.col("time_ms").alias("_b"))
    return left.join(right, "eps").select("eps", (F.col("_b") / F.col("_a")).alias("speedup"))


def mean_trajectory(runs: DataFrame, grid: list[float], by: list[str] = ("method",)) -> DataFrame:
    """Mean gap over runs on a common time grid; a run's value is its last one before the grid time."""
    ticks = runs.select(*by, "run_id").distinct().withColumn("time_ms", F.explode(F.array(*[F.lit(float(g)) for g in grid]))).withColumn("gap", F.lit(None).cast("double")).withColumn("_tick", F.lit(True))
    both = runs.select(*by, "run_id", "time_ms", "gap").withColumn("_tick", F.lit(False)).unionByName(ticks)
    w = Window.partitionBy(*by, "run_id").orderBy("time_ms", "_tick").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("gap", F.last("gap", ignorenulls=True).over(w)).where("_tick").groupBy(*by, "time_ms").agg(F.avg("gap").alias("gap"), F.count("gap").alias("runs"))


def asof_last(left: DataFrame, right: DataFrame, by: str, ts: str, values: list[str]) -> DataFrame:
    """Each left row with the last right values at or before its time, by one sort and no join."""
    marked = right.select(by, ts, *values).withColumn("_l", F.lit(False))
    for c in left.columns:
        if c not in (by, ts):
            marked = marked.withColumn(f"_k_{c}", F.lit(None).cast(left.schema[c].dataType))
    own = left.select(by, ts, *[F.lit(None).cast(right.schema[v].dataType).alias(v) for v in values], F.lit(True).alias("_l"), *[F.col(c).alias(f"_k_{c}") for c in left.columns if c not in (by, ts)])
    w = Window.partitionBy(by).orderBy(ts, "_l").rowsBetween(Window.unboundedPreceding, 0)
    filled = marked.unionByName(own).withColumns({v: F.last(v, ignorenulls=True).over(w) for v in values}).where("_l")
    return filled.select(by, ts, *[F.col(f"_k_{c}").alias(c) for c in left.columns if c not in (by, ts)], *values)


def iteration_latency(ends: DataFrame) -> DataFrame:
    w = Window.orderBy("t")
    return ends.select("t", "end_ms", (F.col("end_ms") - F.coalesce(F.lag("end_ms").over(w), F.lit(0.0))).alias("latency_ms"))


def participation(log: DataFrame, iterations: int) -> DataFrame:
    """Fresh share of each worker."""
    return log.groupBy("worker").agg((F.sum(F.col("fresh").cast("double")) / iterations).alias("u"))


def participation_spread(shares: DataFrame) -> DataFrame:
    return shares.agg((F.max("u") - F.min("u")).alias("spread"), F.stddev_pop("u").alias("sd"))


def within_margin(log: DataFrame, w: int) -> DataFrame:
    """Fresh results beyond the w-th in each iteration."""
    return log.groupBy("arrived_in").agg((F.sum(F.col("fresh").cast("long")) - w).alias("extra"))


def cache_health(log: DataFrame, n: int) -> DataFrame:
    """Rows covered after each arrival, from what it added and evicted."""
    added = F.when(F.col("action").isin("insert", "replace"), F.col("hi") - F.col("lo") + 1 - F.col("rows_evicted")).otherwise(0)
    covered = F.sum(added).over(Window.orderBy("seq").rowsBetween(Window.unboundedPreceding, 0))
    return log.select("seq", "arrived_in", "action", "n_evicted", covered.cast("long").alias("rows_covered")).withColumn("coverage", F.col("rows_covered") / n)


def staleness_histogram(log: DataFrame) -> DataFrame:
    return log.groupBy((F.col("arrived_in") - F.col("version")).alias("staleness"), "action").agg(F.count(F.lit(1)).alias("n"))


def eviction_cost(health: DataFrame, n: int, from_t: int) -> DataFrame:
    """Missing rows summed over the iterations from ``from_t`` on."""
    last = health.groupBy("arrived_in").agg(F.max_by("rows_covered", "seq").alias("rows"))
    return last.where(F.col("arrived_in") >= from_t).agg(F.sum(n - F.col("rows")).alias("missing_row_iterations"))


def work(log: DataFrame, d: int, k: int, density: float = 1.0) -> DataFrame:
    """Operations by what became of the result."""
    ops = 2.0 * density * d * k * (F.col("hi") - F.col("lo") + 1)
    return log.groupBy("action").agg(F.sum(ops).alias("operations"), F.count(F.lit(1)).alias("tasks"))


def plateau(trajectory: DataFrame, tail: int, by: list[str] = ("method",)) -> DataFrame:
    """Least gap over the last ``tail`` measured iterations."""
    w = Window.partitionBy(*by).orderBy(F.col("t").desc())
    return trajectory.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= tail).groupBy(*by).agg(F.min("gap").alias("floor"))


def rate(trajectory: DataFrame, by: list[str] = ("method",)) -> DataFrame:
    """Slope of the logarithm of the gap over the iterations."""
    return trajectory.where("gap > 0").groupBy(*by).agg(F.regr_slope(F.log("gap"), F.col("t").cast("double")).alias("slope"))


def rate_by_phase(trajectory: DataFrame, edges: list[int]) -> DataFrame:
    """The same by phase between the given iterations (such as re-partitionings)."""
    phase = sum((F.when(F.col("t") > e, 1).otherwise(0) for e in edges), F.lit(0))
    return rate(trajectory.withColumn("phase", phase), ["phase"])


def balance_gain(plain: DataFrame, balanced: DataFrame, m: int = 20) -> DataFrame:
    """Mean iteration latency of the last m iterations without and with balancing, and their ratio."""

    def last(df: DataFrame, name: str) -> DataFrame:
        return iteration_latency(df).orderBy(F.col("t").desc()).limit(m).agg(F.avg("latency_ms").alias(name))

    return last(plain, "plain_ms").crossJoin(F.broadcast(last(balanced, "balanced_ms"))).withColumn("gain", F.col("plain_ms") / F.col("balanced_ms"))


def lb_precision_loss(plain: DataFrame, balanced: DataFrame, grid: list[float]) -> DataFrame:
    """Gap with balancing minus gap without at equal times."""
    a = mean_trajectory(plain.withColumn("method", F.lit("p")), grid).select("time_ms", F.col("gap").alias("_p"))
    b = mean_trajectory(balanced.withColumn("method", F.lit("b")), grid).select("time_ms", F.col("gap").alias("_b"))
    return a.join(b, "time_ms").select("time_ms", (F.col("_b") - F.col("_p")).alias("loss"))


def method_rollup(times: DataFrame) -> DataFrame:
    """Mean time by method and level with subtotals."""
    return times.rollup("method", "eps").agg(F.avg("time_ms").alias("mean_ms"), F.count("time_ms").alias("reached"))
