"""Grouped aggregates over vectors and row intervals, for DataFrames and SQL."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql.functions import pandas_udf
from pyspark.sql.types import ArrayType, DoubleType, LongType


@pandas_udf(ArrayType(DoubleType()))
def vector_sum(vectors: pd.Series) -> list:
    """Element-wise sum of equally long vectors; null vectors do not count."""
    kept = [v for v in vectors if v is not None]
    return np.sum(np.stack(kept), axis=0).tolist() if kept else None


@pandas_udf(ArrayType(DoubleType()))
def gram_sum(vectors: pd.Series) -> list:
    """Sum of the outer products of each vector with itself, row by row."""
    kept = [v for v in vectors if v is not None]
    if not kept:
        return None
    x = np.stack(kept)
    return (x.T @ x).ravel().tolist()


@pandas_udf(LongType())
def interval_rows(lo: pd.Series, hi: pd.Series) -> int:
    """Rows in the union of inclusive intervals."""
    if not len(lo):
        return 0
    order = np.argsort(lo.to_numpy(), kind="stable")
    a, b = lo.to_numpy()[order], np.maximum.accumulate(hi.to_numpy()[order])
    reached = np.concatenate(([a[0] - 1], b[:-1]))
    return int(np.maximum(b - np.maximum(a - 1, reached), 0).sum())
