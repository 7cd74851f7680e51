"""SQL surface: scalar functions, table functions and views for users of ``spark.sql``."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import IntegerType

from stalegrad.functions.aggregates import gram_sum, interval_rows, vector_sum
from stalegrad.functions.draws import gamma_cdf_udf, gamma_draws, gamma_quantile_udf, normal_quantile_udf
from stalegrad.operators import partitioning
from stalegrad.operators.simulate import recurrence
from stalegrad.sources.tables import load


@udtf(returnType="k int, lo long, hi long")
class Pieces:
    """pieces(rows, parts): the bounds of every subpartition."""

    def eval(self, rows: int, parts: int) -> Iterator[tuple[int, int, int]]:
        for k in range(1, parts + 1):
            yield k, *partitioning.sub_bounds(rows, parts, k)


@udtf(returnType="step int, old_k int, new_k int, aligned boolean")
class AlignTrace:
    """align_trace(rows, old, new, k): every pair the alignment walk looks at."""

    def eval(self, rows: int, old: int, new: int, k: int) -> Iterator[tuple[int, int, int, bool]]:
        k = partitioning.next_sub(k, old)
        j, step = partitioning.translate(rows, old, new, k), 0
        while True:
            same = partitioning.sub_bounds(rows, old, k)[0] == partitioning.sub_bounds(rows, new, j)[0]
            yield step, k, j, same
            if same:
                return
            j, step = j - 1, step + 1
            if j < 1:
                yield step, 1, 1, True
                return
            k = partitioning.translate(rows, new, old, j)


@udtf(returnType="t int, end_ms double, n_fresh int")
class Simulate:
    """simulate(means, variances, w, iterations, margin, seed): iteration ends of the quorum loop over gamma latencies."""

    def eval(self, means: list, variances: list, w: int, iterations: int, margin: float, seed: int) -> Iterator[tuple[int, float, int]]:
        x = gamma_draws(np.random.default_rng(seed), np.array(means), np.array(variances), (iterations, len(means)))
        s = recurrence(x, w, float(margin))
        for t in range(iterations):
            yield t + 1, float(s.ends[t]), int(s.fresh[t].sum())


@pandas_udf(IntegerType())
def align_udf(rows: pd.Series, old: pd.Series, new: pd.Series, k: pd.Series) -> pd.Series:
    return pd.Series([partitioning.align(*x) for x in zip(rows.tolist(), old.tolist(), new.tolist(), k.tolist(), strict=True)], dtype="int32")


def register(spark: SparkSession, sf_dir: str | None = None) -> None:
    """Registers the functions, and the base tables as views if a folder is given."""
    spark.udf.register("gamma_cdf", gamma_cdf_udf)
    spark.udf.register("gamma_quantile", gamma_quantile_udf)
    spark.udf.register("normal_quantile", normal_quantile_udf)
    for f in (vector_sum, gram_sum, interval_rows):
        spark.udf.register(f.__name__, f)
    spark.udf.register("align_piece", align_udf)
    spark.udtf.register("simulate", Simulate)
    spark.udtf.register("pieces", Pieces)
    spark.udtf.register("align_trace", AlignTrace)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sub_lo(m BIGINT, parts BIGINT, k BIGINT) RETURNS BIGINT RETURN (k - 1) * m DIV parts + 1")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sub_hi(m BIGINT, parts BIGINT, k BIGINT) RETURNS BIGINT RETURN k * m DIV parts")
    if sf_dir:
        for name in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "labels"):
            load(spark, sf_dir, name).createOrReplaceTempView(name)
