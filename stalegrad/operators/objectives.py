"""Finite sums: objectives, subgradients over row intervals, regularisers and projections."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stalegrad.functions.draws import uniform_np


def gram_schmidt(v: np.ndarray) -> np.ndarray:
    """Orthonormal columns with a positive diagonal of the triangular factor."""
    q, r = np.linalg.qr(v)
    return q * np.where(np.diag(r) < 0, -1.0, 1.0)


def distributed_gram_schmidt(rows: DataFrame, k: int) -> DataFrame:
    """Orthonormal columns of a tall iterate (col, v array<double>) that never leaves the executors.

    Only the k x k Gram matrix is collected; its Cholesky factor R gives V R^-1,
    which has the same columns as Gram-Schmidt with a positive diagonal.
    """
    cells = [F.sum(F.col("v")[i] * F.col("v")[j]).alias(f"g{i}_{j}") for i in range(k) for j in range(i, k)]
    got = rows.agg(*cells).first()
    gram = np.array([[got[f"g{min(i, j)}_{max(i, j)}"] for j in range(k)] for i in range(k)], dtype=float)
    inverse = np.linalg.inv(np.linalg.cholesky(gram).T)
    turned = [sum((F.col("v")[i] * float(inverse[i, c]) for i in range(c + 1)), F.lit(0.0)) for c in range(k)]
    return rows.select("col", F.array(*turned).alias("v"))


def _softplus(z: np.ndarray) -> np.ndarray:
    return np.logaddexp(0.0, z)


class _Linear:
    """Objectives of the products z = x v: a part is x' pull(z, y), a value the sum of row values."""

    lam: float = 0.0

    def start(self, seed: int = 0) -> np.ndarray:
        return np.zeros((self.d, 1))

    def part(self, x: np.ndarray, y: np.ndarray, v: np.ndarray) -> np.ndarray:
        return x.T @ self.pull(x @ v, y)

    def rows_value(self, z: np.ndarray, y: np.ndarray) -> float:
        """The sum of the row values."""
        return float(self.row_values(z, y).sum())

    def value(self, x, y, v) -> float:
        return self.rows_value(x @ v, y) + self.regulariser(v)

    def regulariser(self, v: np.ndarray) -> float:
        return float(self.lam / 2 * (v * v).sum())

    def regulariser_grad(self, v: np.ndarray) -> np.ndarray:
        return self.lam * v

    def project(self, v: np.ndarray) -> np.ndarray:
        return v


@dataclass
class Logistic(_Linear):
    """Mean logistic loss with an L2 term on the whole iterate; the mean's 1/n is inside each part."""

    n: int
    d: int
    lam: float | None = None
    k: int = 1

    def __post_init__(self):
        self.lam = 1.0 / self.n if self.lam is None else self.lam

    def pull(self, z: np.ndarray, y: np.ndarray) -> np.ndarray:
        y = y[:, None]
        return -y / (1 + np.exp(np.clip(y * z, -700, 700))) / self.n

    def row_values(self, z: np.ndarray, y: np.ndarray) -> np.ndarray:
        return _softplus(-y * z[:, 0]) / self.n

    def rows_value(self, z: np.ndarray, y: np.ndarray) -> float:
        """With one logarithm for 512 rows: their factors 1 + exp(-|m|) are at most 2 and are multiplied first."""
        margin = -y * z[:, 0]
        factors = 1 + np.exp(-np.abs(margin))
        logs = np.log(np.multiply.reduceat(factors, np.arange(0, len(factors), 512))).sum() if len(factors) else 0.0
        return float(np.maximum(margin, 0.0).sum() + logs) / self.n

    def pull_columns(self, z: list[Column], y: Column) -> list[Column]:
        return [-y / (1 + F.exp(y * z[0])) / self.n]

    def value_column(self, z: list[Column], y: Column) -> Column:
        margin = -y * z[0]
        return (F.greatest(margin, F.lit(0.0)) + F.log1p(F.exp(-F.abs(margin)))) / self.n

    def curvature(self, z: np.ndarray, y: np.ndarray) -> np.ndarray:
        share = 1 / (1 + np.exp(-np.clip(z[:, 0], -700, 700)))
        return share * (1 - share) / self.n

    def curvature_column(self, z: list[Column], y: Column) -> Column:
        share = 1 / (1 + F.exp(-z[0]))
        return share * (1 - share) / self.n

    def loss(self, x: np.ndarray, y: np.ndarray, v: np.ndarray) -> float:
        return float(self.row_values(x @ v, y).sum())

    def optimum(self, x, y) -> float:
        """Newton's method; ``d`` is small."""
        v = self.start()
        for _ in range(60):
            p = 1 / (1 + np.exp(-(x @ v[:, 0])))
            grad = self.part(x, y, v) + self.lam * v
            hess = (x * (p * (1 - p))[:, None]).T @ x / self.n + self.lam * np.eye(self.d)
            step = np.linalg.solve(hess, grad)
            v = v - step
            if np.abs(step).max() < 1e-13:
                break
        return self.value(x, y, v)


@dataclass
class LeastSquares(_Linear):
    """Half the mean squared error with an L2 term."""

    n: int
    d: int
    lam: float = 0.0
    k: int = 1

    def pull(self, z, y):
        return (z - y[:, None]) / self.n

    def row_values(self, z, y):
        return (z[:, 0] - y) ** 2 / (2 * self.n)

    def pull_columns(self, z, y):
        return [(z[0] - y) / self.n]

    def value_column(self, z, y):
        return (z[0] - y) * (z[0] - y) / (2 * self.n)

    def curvature(self, z, y):
        return np.full(len(z), 1.0 / self.n)

    def curvature_column(self, z, y):
        return F.lit(1.0 / self.n)

    def optimum(self, x, y) -> float:
        v = np.linalg.solve(x.T @ x / self.n + self.lam * np.eye(self.d), x.T @ y / self.n)
        return self.value(x, y, v[:, None])


@dataclass
class PCA(_Linear):
    """Top-k subspace: the gradient simplified under orthonormal columns, a power step at step size 1.

    The value is minus the explained share of variance, so a gap is the share lost.
    The first iterate is made of hashed uniforms, the same for any engine.
    """

    n: int
    d: int
    k: int = 3
    norm: float = 1.0  # squared Frobenius norm of the matrix

    def start(self, seed: int = 0) -> np.ndarray:
        return gram_schmidt(np.array([[uniform_np(seed, i, c) - 0.5 for c in range(self.k)] for i in range(self.d)]))

    def pull(self, z, y):
        return -z

    def row_values(self, z, y):
        return -(z * z).sum(axis=1) / self.norm

    def pull_columns(self, z, y):
        return [-c for c in z]

    def value_column(self, z, y):
        return -sum((c * c for c in z), F.lit(0.0)) / self.norm

    def regulariser(self, v):
        return 0.0

    def regulariser_grad(self, v):
        return v

    def project(self, v):
        return gram_schmidt(v)

    def optimum(self, x, y) -> float:
        gram = x.T @ x if x.shape[0] >= x.shape[1] else x @ x.T
        return -float(np.sort(np.linalg.eigvalsh(gram))[::-1][: self.k].sum()) / self.norm


def explained_variance(x: np.ndarray, v: np.ndarray) -> float:
    return float(((x @ v) ** 2).sum() / (x * x).sum())


def power_iteration(x: np.ndarray, v: np.ndarray, steps: int) -> np.ndarray:
    for _ in range(steps):
        v = gram_schmidt(x.T @ (x @ v))
    return v
