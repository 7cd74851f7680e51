"""Latency of the w-th fastest worker: measured, sampled and exact."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stalegrad.functions.draws import gamma_cdf, uniform
from stalegrad.operators.simulate import draws


def empirical_order_stats(trace: DataFrame, n_workers: int) -> DataFrame:
    """Mean latency of the w-th fastest over iterations in which every worker has a recording."""
    whole = trace.groupBy("t").agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") == n_workers)
    rank = F.row_number().over(Window.partitionBy("t").orderBy("round_trip_ms", "worker"))
    return trace.join(whole, "t", "left_semi").withColumn("w", rank).groupBy("w").agg(F.avg("round_trip_ms").alias("mean_ms"))


def predict_order_stats(spark: SparkSession, stats: DataFrame, count: int, seed: int = 0, model: str = "gamma") -> DataFrame:
    """(w, mean_ms, var_ms, p95_ms) for every w by Monte Carlo over the workers' gammas.

    ``model='iid_gamma'`` and ``'iid_shifted_exp'`` give every worker the pooled
    distribution (within- plus between-worker variance).
    """
    table = stats.orderBy("worker").toPandas()
    if model.startswith("iid"):
        for part in ("comm", "comp"):
            e, v = table[f"e_{part}"], table[f"v_{part}"].fillna(0)
            table[f"v_{part}"] = v.mean() + e.var(ddof=0)
            table[f"e_{part}"] = e.mean()

    def sample(rng: np.random.Generator, rows: int) -> np.ndarray:
        if model == "iid_shifted_exp":
            sd = np.sqrt(table["v_comm"] + table["v_comp"]).to_numpy()
            return (table["e_comm"] + table["e_comp"]).to_numpy() - sd + rng.exponential(size=(rows, len(table))) * sd
        return draws(table, rows, rng)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for r in batch["replicate"]:  # a replicate here is a block of 64 draws
                x = np.sort(sample(np.random.default_rng([seed, int(r)]), 64), axis=1)
                yield pd.DataFrame({"w": np.tile(np.arange(1, x.shape[1] + 1), 64), "ms": x.ravel()})

    ids = spark.range(0, -(-count // 64), 1, spark.sparkContext.defaultParallelism).withColumnRenamed("id", "replicate")
    drawn = ids.mapInPandas(run, "w int, ms double")
    return drawn.groupBy("w").agg(F.avg("ms").alias("mean_ms"), F.var_samp("ms").alias("var_ms"), F.percentile_approx("ms", 0.95).alias("p95_ms"))


def hashed_order_stats(rates: DataFrame, count: int, seed: int = 0) -> DataFrame:
    """(w, mean_ms) by shifted-exponential inversion of hashed uniforms, in SQL terms only."""
    replicate = F.explode(F.sequence(F.lit(1), F.lit(count)))
    drawn = rates.withColumn("r", replicate).withColumn("ms", F.col("shift") - F.log(uniform(seed, F.col("r"), F.col("worker"))) / F.col("rate"))
    rank = F.row_number().over(Window.partitionBy("r").orderBy("ms", "worker"))
    return drawn.withColumn("w", rank).groupBy("w").agg(F.avg("ms").alias("mean_ms"))


def exact_order_stat(shapes: np.ndarray, scales: np.ndarray, w: int, points: int = 4000) -> float:
    """Mean of the w-th smallest of independent gammas: the chance of at least w successes, integrated."""
    top = float(np.max(shapes * scales + 12 * np.sqrt(shapes) * scales))
    grid = np.linspace(0, top, points)
    below = gamma_cdf(grid[:, None], shapes[None], scales[None])
    chance = np.zeros((points, len(shapes) + 1))
    chance[:, 0] = 1
    for i in range(len(shapes)):
        p = below[:, i : i + 1]
        chance[:, 1:] = chance[:, 1:] * (1 - p) + chance[:, :-1] * p
        chance[:, 0] *= 1 - p[:, 0]
    return float(np.trapezoid(chance[:, :w].sum(axis=1), grid))
