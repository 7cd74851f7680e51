"""The latency model: traces, moments, fits, bursts and scripted slowdowns.

A trace row is one task of one worker: ``comp_ms`` measured by the worker and
``comm_ms``, the rest of the round trip.  Workers are numbered from 1.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stalegrad.functions.draws import gamma_cdf_udf, gamma_scale, gamma_shape


def trace_from_events(events: DataFrame, n_workers: int, base_ms: float = 1000.0, ramp: float = 0.0) -> DataFrame:
    """Events as recordings: the user picks the worker, ``value`` the work, ``props.k`` the transfer.

    ``ramp`` slows worker i by the factor 1 + ramp * i / N.
    """
    worker = (F.pmod("user_id", F.lit(n_workers)) + 1).cast("int")
    k = F.get_json_object("props", "$.k").cast("double")
    order = Window.partitionBy("worker").orderBy("ts", "event_id")
    comp = (F.lit(base_ms) + F.col("value")) * (1 + F.lit(ramp) * F.col("worker") / n_workers)
    rows = events.select("event_id", "ts", "value", "props", worker.alias("worker")).withColumns({"comm_ms": k / 10 + 0.1, "comp_ms": comp})
    return rows.select("worker", F.row_number().over(order).cast("int").alias("t"), "event_id", "ts", "comm_ms", "comp_ms", (F.col("comm_ms") + F.col("comp_ms")).alias("round_trip_ms"))


def worker_stats(trace: DataFrame) -> DataFrame:
    return trace.groupBy("worker").agg(
        F.count(F.lit(1)).alias("n_obs"),
        F.avg("comm_ms").alias("e_comm"), F.var_samp("comm_ms").alias("v_comm"),
        F.avg("comp_ms").alias("e_comp"), F.var_samp("comp_ms").alias("v_comp"),
    )


def gamma_moments(stats: DataFrame, part: str = "comp") -> DataFrame:
    e, v = F.col(f"e_{part}"), F.col(f"v_{part}")
    return stats.select("worker", gamma_shape(e, v).alias("shape"), gamma_scale(e, v).alias("scale"))


def total_moments(stats: DataFrame) -> DataFrame:
    """Mean and variance of the whole latency, the parts being independent."""
    return stats.select("worker", (F.col("e_comm") + F.col("e_comp")).alias("e_total"), (F.col("v_comm") + F.col("v_comp")).alias("v_total"))


def empirical_cdf(trace: DataFrame, column: str = "round_trip_ms") -> DataFrame:
    w = Window.partitionBy("worker").orderBy(column)
    return trace.select("worker", F.col(column).alias("latency"), F.cume_dist().over(w).alias("cdf"))


def ks_distance(trace: DataFrame, stats: DataFrame) -> DataFrame:
    """Largest gap between a worker's empirical and fitted computation CDF (both sides of each step)."""
    w = Window.partitionBy("worker").orderBy("comp_ms")
    n = F.count(F.lit(1)).over(Window.partitionBy("worker"))
    points = trace.select("worker", "comp_ms", F.rank().over(w).alias("_r"), F.cume_dist().over(w).alias("cdf"), n.alias("_n"))
    fitted = points.join(F.broadcast(gamma_moments(stats)), "worker").withColumn("fit", gamma_cdf_udf("comp_ms", "shape", "scale"))
    gap = F.greatest(F.abs(F.col("cdf") - F.col("fit")), F.abs((F.col("_r") - 1) / F.col("_n") - F.col("fit")))
    return fitted.groupBy("worker").agg(F.max(gap).alias("distance"))


def comm_comp_corr(trace: DataFrame) -> DataFrame:
    return trace.groupBy("worker").agg(F.corr("comm_ms", "comp_ms").alias("corr"))


def slowness(stats: DataFrame) -> DataFrame:
    """Expected latency of each worker over that of the fastest."""
    total = total_moments(stats)
    fastest = total.agg(F.min("e_total").alias("least"))
    return total.crossJoin(F.broadcast(fastest)).select("worker", (F.col("e_total") / F.col("least")).alias("slowness"))


def load_points(trace: DataFrame, loads: list[int]) -> DataFrame:
    """Latency of c consecutive recordings of a worker taken as one task of load c."""
    sized = trace.withColumn("load", F.explode(F.array(*[F.lit(c) for c in loads])))
    blocks = sized.groupBy("worker", "load", F.floor((F.col("t") - 1) / F.col("load")).alias("block")).agg(F.sum("comp_ms").alias("comp"), F.count(F.lit(1)).alias("n"))
    full = blocks.where("n = load")
    return full.groupBy("worker", "load").agg(F.avg("comp").alias("mean"), F.var_samp("comp").alias("variance"))


def origin_fit(points: DataFrame) -> DataFrame:
    """Least-squares line through the origin for mean and variance against load, with its R squared."""
    long = points.select("load", F.explode(F.map_from_arrays(F.array(F.lit("mean"), F.lit("variance")), F.array("mean", "variance"))).alias("what", "y")).where("y IS NOT NULL")
    x, y = F.col("load"), F.col("y")
    return long.groupBy("what").agg((F.sum(x * y) / F.sum(x * x)).alias("slope"), F.sum(x * y).alias("xy"), F.sum(x * x).alias("xx"), F.sum(y * y).alias("yy")).select("what", "slope", (F.col("xy") * F.col("xy") / (F.col("xx") * F.col("yy"))).alias("r2"))


def iid_stats(trace: DataFrame) -> DataFrame:
    """One distribution for all workers: global mean and variance of each part."""
    return trace.agg(F.avg("comm_ms").alias("e_comm"), F.var_samp("comm_ms").alias("v_comm"), F.avg("comp_ms").alias("e_comp"), F.var_samp("comp_ms").alias("v_comp"))


def shifted_exp_moments(stats: DataFrame) -> DataFrame:
    """Shift plus exponential with the same mean and variance."""
    sd = F.sqrt("v_comp")
    return stats.select("worker", (1 / sd).alias("rate"), (F.col("e_comp") - sd).alias("shift"))


def two_level_fit(trace: DataFrame) -> DataFrame:
    """Two values a worker: means below and above its own mean, and the share above."""
    mean = F.avg("comp_ms").over(Window.partitionBy("worker"))
    split = trace.select("worker", "comp_ms", (F.col("comp_ms") > mean).alias("high"))
    return split.groupBy("worker").agg(
        F.avg(F.when(~F.col("high"), F.col("comp_ms"))).alias("low_ms"),
        F.avg(F.when(F.col("high"), F.col("comp_ms"))).alias("high_ms"),
        F.avg(F.col("high").cast("double")).alias("p_high"),
    )


def slow_ramp(stats: DataFrame, n_workers: int, amount: float = 0.4, release: Column | None = None) -> DataFrame:
    """Computation of worker i times 1 + amount * i / N; ``release`` marks workers let off."""
    factor = 1 + F.lit(amount) * F.col("worker") / n_workers
    if release is not None:
        factor = F.when(release, F.lit(1.0)).otherwise(factor)
    return stats.withColumns({"e_comp": F.col("e_comp") * factor, "v_comp": F.col("v_comp") * factor * factor})


def perturb(trace: DataFrame, script: DataFrame) -> DataFrame:
    """Applies a script (worker, from_t, to_t, factor) to the computation part; overlapping lines multiply."""
    hit = (F.col("t") >= F.col("from_t")) & (F.col("t") < F.col("to_t"))
    marked = trace.join(F.broadcast(script), "worker", "left").withColumn("_f", F.when(hit, F.log("factor")).otherwise(0.0))
    keys = [c for c in trace.columns if c not in ("comp_ms", "round_trip_ms")]
    out = marked.groupBy(*keys, "comp_ms").agg(F.exp(F.sum("_f")).alias("_f")).withColumn("comp_ms", F.col("comp_ms") * F.col("_f"))
    return out.withColumn("round_trip_ms", F.col("comm_ms") + F.col("comp_ms")).select(*trace.columns)


def bursts(trace: DataFrame, window: int = 9, factor: float = 1.12) -> DataFrame:
    """Islands where a worker's centred rolling mean exceeds its median by ``factor``."""
    half = window // 2
    per = Window.partitionBy("worker")
    rolling = F.avg("comp_ms").over(per.orderBy("t").rowsBetween(-half, half))
    baseline = trace.groupBy("worker").agg(F.percentile("comp_ms", F.lit(0.5)).alias("_base"))
    marked = trace.select("worker", "t", rolling.alias("_roll")).join(F.broadcast(baseline), "worker").where(F.col("_roll") > factor * F.col("_base"))
    island = F.col("t") - F.row_number().over(per.orderBy("t"))
    return marked.withColumn("_island", island).groupBy("worker", "_island").agg(F.min("t").alias("start_t"), F.max("t").alias("end_t"), F.count(F.lit(1)).alias("n")).drop("_island")


def burst_share(trace: DataFrame, found: DataFrame) -> DataFrame:
    """Share of iterations with a worker in a burst, and the number of workers that had one."""
    ts = trace.select("t").distinct()
    spans = found.select(F.explode(F.sequence("start_t", "end_t")).alias("t"), "worker")
    hit = ts.join(spans.select("t").distinct(), "t", "left_semi").agg(F.count(F.lit(1)).alias("_hit"))
    workers = found.agg(F.countDistinct("worker").alias("workers"))
    total = ts.agg(F.count(F.lit(1)).alias("_all"))
    return total.crossJoin(F.broadcast(hit)).crossJoin(F.broadcast(workers)).select((F.col("_hit") / F.col("_all")).alias("share"), "workers")


def no_burst_probability(share_per_worker: Column, n_workers: Column) -> Column:
    return F.pow(1 - share_per_worker, n_workers)


def moving_profile(trace: DataFrame, window: str = "1 day") -> DataFrame:
    """Moments over each worker's recordings in (ts - window, ts]; one recording gives no variance.

    A worker's recordings are dealt by stretches of one window, each together with the
    stretch before it, so a task holds two windows of one worker.  The sums of every
    window are differences of running sums about the mean, in extended precision.
    """
    span = int(_micros(window))
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    copies = F.explode(F.when(F.col("_us").isNull(), F.array(F.lit(0))).otherwise(F.array(F.lit(0), F.lit(1)))).alias("_later")
    kept = trace.select("worker", "event_id", "ts", "comm_ms", "comp_ms", us.alias("_us")).select("*", copies)
    dealt = kept.withColumn("_stretch", F.floor(F.col("_us") / span) + F.col("_later"))
    kinds = {f.name: f.dataType.simpleString() for f in trace.schema}
    schema = f"worker {kinds['worker']}, event_id {kinds['event_id']}, ts {kinds['ts']}, n_win long, e_comm double, v_comm double, e_comp double, v_comp double"

    def profile(table: pa.Table) -> pa.Table:
        if table["_us"].null_count:  # recordings without a time are in force together
            at, first, last = np.arange(len(table)), np.zeros(len(table), dtype=int), np.full(len(table), len(table))
            own = at
        else:
            us = table["_us"].to_numpy()
            at = np.argsort(us, kind="stable")
            us = us[at]
            own = np.flatnonzero(table["_later"].to_numpy()[at] == 0)
            first, last = np.searchsorted(us, us[own] - span, "right"), np.searchsorted(us, us[own], "right")
        out = [table[c].take(pa.array(at[own])) for c in ("worker", "event_id", "ts")] + [pa.array(last - first, pa.int64())]
        for c in ("comm_ms", "comp_ms"):
            known = table[c].is_valid().to_numpy()[at]
            out += _window_moments(table[c].fill_null(0.0).to_numpy()[at], known, first, last)
        return pa.table(out, names=["worker", "event_id", "ts", "n_win", "e_comm", "v_comm", "e_comp", "v_comp"])

    return dealt.groupBy("worker", "_stretch").applyInArrow(profile, schema)


def _window_moments(x: np.ndarray, known: np.ndarray, first: np.ndarray, last: np.ndarray) -> list[pa.Array]:
    """Mean and sample variance of the known values x[first:last] of every window; null where there are too few."""

    def within(cells: np.ndarray) -> np.ndarray:
        running = np.concatenate((np.zeros(1, cells.dtype), np.cumsum(cells)))
        return running[last] - running[first]

    plain = known & np.isfinite(x)
    centre = x[plain].mean() if plain.any() else 0.0
    off = np.where(plain, x - centre, 0.0).astype(np.longdouble)
    n = within(known.astype(np.int64))
    total, squares = within(off), within(off * off)
    mean = (centre + total / np.maximum(n, 1)).astype(float)
    variance = (np.maximum(squares - total * total / np.maximum(n, 1), 0) / np.maximum(n - 1, 1)).astype(float)
    if not plain[known].all():  # infinities and NaN only spoil the windows they are in
        high, low, none = (within((known & hit).astype(np.int64)) > 0 for hit in (x == np.inf, x == -np.inf, np.isnan(x)))
        mean = np.where(high, np.inf, np.where(low, -np.inf, mean))
        mean = np.where(none | (high & low), np.nan, mean)
        variance = np.where(none | high | low, np.nan, variance)
    return [pa.array(mean, mask=n < 1), pa.array(variance, mask=n < 2)]


def _micros(window: str) -> float:
    number, unit = window.split()
    return float(number) * {"second": 1, "minute": 60, "hour": 3600, "day": 86400}[unit.rstrip("s")] * 1e6


def latency_ranges(trace: DataFrame) -> DataFrame:
    """Least and greatest worker mean of each part."""
    means = trace.groupBy("worker").agg(F.avg("comm_ms").alias("comm"), F.avg("comp_ms").alias("comp"))
    long = means.select(F.explode(F.map_from_arrays(F.array(F.lit("comm"), F.lit("comp")), F.array("comm", "comp"))).alias("part", "mean_ms"))
    return long.groupBy("part").agg(F.min("mean_ms").alias("min_ms"), F.max("mean_ms").alias("max_ms"))
