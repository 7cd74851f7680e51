"""Reproducible draws and the gamma distribution.

A uniform is made from the first twelve hex digits of an MD5 over its
coordinates, so Spark, SQL engines and NumPy give the same number whatever the
partitioning.
"""

from __future__ import annotations

import hashlib
import math
from statistics import NormalDist

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf
from pyspark.sql.types import DoubleType


def uniform(seed: int | str, *parts: Column) -> Column:
    """(first 48 bits of md5('seed|a|b|...') + 1/2) / 2**48 as a column."""
    text = F.concat_ws("|", F.lit(str(seed)), *[p.cast("string") for p in parts])
    return (F.conv(F.substring(F.md5(text.cast("binary")), 1, 12), 16, 10).cast("double") + 0.5) / float(1 << 48)


def uniform_np(seed: int | str, *parts: int | str) -> float:
    text = "|".join([str(seed), *map(str, parts)])
    return (int(hashlib.md5(text.encode()).hexdigest()[:12], 16) + 0.5) / float(1 << 48)


def gamma_shape(mean: Column, variance: Column) -> Column:
    """Shape by matching moments; null where the variance is not positive (a point mass)."""
    return F.when(variance > 0, mean * mean / variance)


def gamma_scale(mean: Column, variance: Column) -> Column:
    return F.when(variance > 0, variance / mean)


def gamma_cdf(x: np.ndarray, shape: np.ndarray, scale: np.ndarray) -> np.ndarray:
    """Regularised lower incomplete gamma: a series left of shape + 1, a continued fraction right of it."""
    x, a, s = np.broadcast_arrays(np.asarray(x, float), np.asarray(shape, float), np.asarray(scale, float))
    z = np.maximum(x, 0) / s
    out = np.zeros(z.shape)
    log_gamma = np.vectorize(math.lgamma, otypes=[float])(a)
    front = np.exp(a * np.log(np.maximum(z, 1e-300)) - z - log_gamma)
    left = (z < a + 1) & (z > 0)
    if left.any():
        term = 1 / a[left]
        total, n = term.copy(), a[left].copy()
        for _ in range(10_000):
            n += 1
            term = term * z[left] / n
            total += term
            if (term < total * 1e-15).all():
                break
        out[left] = total * front[left]
    right = z >= a + 1
    if right.any():
        b = z[right] + 1 - a[right]
        c = np.full(b.shape, 1e300)
        d = 1 / b
        h = d.copy()
        for i in range(1, 10_000):
            step = -i * (i - a[right])
            b = b + 2
            d = step * d + b
            d[np.abs(d) < 1e-300] = 1e-300
            c = b + step / c
            c[np.abs(c) < 1e-300] = 1e-300
            d = 1 / d
            h = h * d * c
            if (np.abs(d * c - 1) < 1e-15).all():
                break
        out[right] = 1 - front[right] * h
    return np.clip(out, 0, 1)


@pandas_udf(DoubleType())
def gamma_cdf_udf(x: pd.Series, shape: pd.Series, scale: pd.Series) -> pd.Series:
    return pd.Series(gamma_cdf(x.to_numpy(), shape.to_numpy(), scale.to_numpy()))


def gamma_quantile(u: np.ndarray, shape: np.ndarray, scale: np.ndarray) -> np.ndarray:
    """The gamma variate whose CDF is u, by bisection; a hashed uniform makes it a reproducible draw."""
    u, a, s = np.broadcast_arrays(np.asarray(u, float), np.asarray(shape, float), np.asarray(scale, float))
    low, high = np.zeros(u.shape), a * s + 1.0 * s
    while (grow := gamma_cdf(high, a, s) < np.minimum(u, 1 - 1e-15)).any():
        high = np.where(grow, 2 * high, high)
    for _ in range(80):
        middle = (low + high) / 2
        under = gamma_cdf(middle, a, s) < u
        low, high = np.where(under, middle, low), np.where(under, high, middle)
    return (low + high) / 2


def normal_quantile(u: np.ndarray) -> np.ndarray:
    """The standard normal variate whose CDF is u."""
    return np.array([NormalDist().inv_cdf(min(max(x, 1e-16), 1 - 1e-16)) for x in np.asarray(u, float).ravel()]).reshape(np.shape(u))


@pandas_udf(DoubleType())
def gamma_quantile_udf(u: pd.Series, shape: pd.Series, scale: pd.Series) -> pd.Series:
    return pd.Series(gamma_quantile(u.to_numpy(), shape.to_numpy(), scale.to_numpy()))


@pandas_udf(DoubleType())
def normal_quantile_udf(u: pd.Series) -> pd.Series:
    return pd.Series(normal_quantile(u.to_numpy()))


def gamma_draws(rng: np.random.Generator, mean: np.ndarray, variance: np.ndarray, size: tuple[int, ...]) -> np.ndarray:
    """Gamma variates by moments; the mean itself where the variance is 0."""
    mean, variance = np.asarray(mean, float), np.asarray(variance, float)
    safe = np.where(variance > 0, variance, 1.0)
    draws = rng.gamma(np.maximum(mean, 1e-12) ** 2 / safe, safe / np.maximum(mean, 1e-12), size)
    return np.where(variance > 0, draws, mean)
