"""Subgradients over many row intervals in one job, by three kernels.

``LocalKernel`` keeps a small matrix (checked size) in one process; the Spark
kernels read only the rows of the asked intervals: ``ExpressionKernel`` sums
column expressions inside whole-stage code for few dense columns,
``BlockKernel`` keeps such rows as arrays on the executors for long runs,
``ArrowKernel`` multiplies dense or sparse batches and adds partial sums per
task before the exchange.  Only d x k numbers an interval reach the driver.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stalegrad.functions.aggregates import vector_sum
from stalegrad.functions.draws import uniform_np
from stalegrad.operators.objectives import gram_schmidt

#: Largest matrix (bytes as doubles) that may be collected into one process.
LOCAL_LIMIT_BYTES = 64 << 20
#: Dense rows (bytes as doubles) that a task multiplies at once.
BLOCK_BYTES = 4 << 20


class LocalKernel:
    """Rows 1..n as one array; intervals are slices."""

    def __init__(self, x: np.ndarray, y: np.ndarray | None = None):
        self.x, self.y = x, np.zeros(len(x)) if y is None else y

    @property
    def n(self) -> int:
        return len(self.x)

    def parts(self, objective, tasks: list[tuple[int, int]], v: np.ndarray) -> list[np.ndarray]:
        return [objective.part(self.x[lo - 1 : hi], self.y[lo - 1 : hi], v) for lo, hi in tasks]

    def value(self, objective, v: np.ndarray) -> float:
        return objective.value(self.x, self.y, v)


def dense_columns(matrix: DataFrame) -> list[str]:
    return sorted((c for c in matrix.columns if c.startswith("x") and c[1:].isdigit()), key=lambda c: int(c[1:]))


def local_logistic(matrix: DataFrame) -> LocalKernel:
    cols = dense_columns(matrix)
    n = matrix.count()
    if n * len(cols) * 8 > LOCAL_LIMIT_BYTES:
        raise ValueError("the matrix is too large for one process; use a Spark kernel")
    table = matrix.orderBy("sample_idx").toPandas()
    return LocalKernel(table[cols].to_numpy(float), table["label"].to_numpy(float))


def local_sparse(matrix: DataFrame, d: int) -> LocalKernel:
    n = matrix.count()
    if n * d * 8 > LOCAL_LIMIT_BYTES:
        raise ValueError("the matrix is too large for one process; use a Spark kernel")
    x = np.zeros((n, d))
    for i, nz in enumerate(matrix.orderBy("sample_idx").toPandas()["nz"]):
        x[i, nz] = 1.0
    return LocalKernel(x)


def _ranges(tasks: list[tuple[int, int]]):
    """One predicate over all asked intervals (merged), which the Parquet scan can use."""
    merged: list[list[int]] = []
    for lo, hi in sorted(tasks):
        if merged and lo <= merged[-1][1] + 1:
            merged[-1][1] = max(hi, merged[-1][1])
        else:
            merged.append([lo, hi])
    out = F.lit(False)
    for lo, hi in merged:
        out = out | F.col("sample_idx").between(lo, hi)
    return out


class ExpressionKernel:
    """Subgradients by column expressions over x0..x{d-1} and label; the objective supplies the row formula."""

    def __init__(self, matrix: DataFrame, n: int):
        self.matrix, self.n, self.cols = matrix, n, dense_columns(matrix)

    def products(self, v: np.ndarray) -> list:
        return [sum((F.col(x) * float(v[i, c]) for i, x in enumerate(self.cols)), F.lit(0.0)) for c in range(v.shape[1])]

    def frame(self, objective, tasks: list[tuple[int, int]], v: np.ndarray) -> DataFrame:
        """(lo, g0, g1, ...): the sums of every interval of ``tasks`` (disjoint); with k columns g{i}_{c}."""
        rows = self.matrix.where(_ranges(tasks))
        if len(tasks) <= 128:  # few: a plain expression, no job for a broadcast
            lo = F.coalesce(*[F.when(F.col("sample_idx").between(a, b), F.lit(a)) for a, b in tasks])
            rows = rows.withColumn("lo", lo.cast("long"))
        else:
            spans = self.matrix.sparkSession.createDataFrame([(int(a), int(b)) for a, b in tasks], "lo long, hi long")
            rows = rows.join(F.broadcast(spans), F.col("sample_idx").between(F.col("lo"), F.col("hi")))
        pulls = objective.pull_columns(self.products(v), F.col("label"))
        return rows.groupBy("lo").agg(*[F.sum(pull * F.col(x)).alias(_cell(i, c, len(pulls))) for i, x in enumerate(self.cols) for c, pull in enumerate(pulls)])

    def parts(self, objective, tasks, v):
        k = v.shape[1]
        found = {r["lo"]: np.array([[r[_cell(i, c, k)] for c in range(k)] for i in range(len(self.cols))]) for r in self.frame(objective, tasks, v).collect()}
        zero = np.zeros((len(self.cols), k))
        return [found.get(lo, zero) for lo, _ in tasks]

    def value(self, objective, v: np.ndarray) -> float:
        total = self.matrix.agg(F.sum(objective.value_column(self.products(v), F.col("label")))).first()[0]
        return (total or 0.0) + objective.regulariser(v)

    def hessian(self, objective, v: np.ndarray) -> np.ndarray:
        """The sum of curvature times x x', one aggregate job."""
        weight, d = objective.curvature_column(self.products(v), F.col("label")), len(self.cols)
        got = self.matrix.agg(*[F.sum(weight * F.col(self.cols[i]) * F.col(self.cols[j])).alias(f"h{i}_{j}") for i in range(d) for j in range(i, d)]).first()
        return np.array([[got[f"h{min(i, j)}_{max(i, j)}"] for j in range(d)] for i in range(d)])

    def optimum(self, objective) -> float:
        """Newton's method over the distributed rows."""
        v = objective.start()
        for _ in range(60):
            grad = self.parts(objective, [(1, self.n)], v)[0] + objective.regulariser_grad(v)
            step = np.linalg.solve(self.hessian(objective, v) + objective.lam * np.eye(len(self.cols)), grad)
            v = v - step
            if np.abs(step).max() < 1e-12:
                break
        return self.value(objective, v)


class BlockKernel:
    """Few dense columns as arrays kept on the executors (memory, then disk); one job answers many runs.

    A request is (iterate, intervals, whether the value is asked).  Requests of equal
    iterates are joined, so runs that share a trajectory pay for it once.  Partial
    sums are added per task and then in the order of the tasks.
    """

    def __init__(self, matrix: DataFrame, n: int):
        from pyspark import StorageLevel

        self.matrix, self.n, self.cols = matrix, n, dense_columns(matrix)
        width = len(self.cols)
        per_block = max(1, BLOCK_BYTES // (8 * width))

        def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held, size = [], 0

            def block() -> pa.RecordBatch:
                table = pa.Table.from_batches(held)
                ids = table.column(0).to_numpy()
                order = np.argsort(ids, kind="stable")
                x = np.stack([table.column(2 + i).to_numpy()[order] for i in range(width)], axis=1)
                arrays = (ids[order], table.column(1).to_numpy()[order], x)
                return pa.RecordBatch.from_arrays([pa.array([a.tobytes()], pa.binary()) for a in arrays], names=["ids", "y", "x"])

            for batch in batches:
                held.append(batch)
                size += batch.num_rows
                if size >= per_block:
                    yield block()
                    held, size = [], 0
            if size:
                yield block()

        def unpack(row):
            return np.frombuffer(row[0], np.int64), np.frombuffer(row[1]), np.frombuffer(row[2]).reshape(-1, width)

        rows = matrix.select(F.col("sample_idx").cast("long"), F.col("label").cast("double"), *[F.col(c).cast("double") for c in self.cols])
        self.blocks = rows.mapInArrow(pack, "ids binary, y binary, x binary").rdd.map(unpack).persist(StorageLevel(True, True, False, True))

    def close(self) -> None:
        self.blocks.unpersist()

    def _sums(self, cells) -> dict:
        """Sums by key of what ``cells(ids, y, x)`` gives for every block, in one job."""

        def add(found: dict, items) -> dict:
            for key, part in items:
                found[key] = found[key] + part if key in found else part
            return found

        def task(blocks) -> Iterator[dict]:
            found: dict = {}
            for block in blocks:
                add(found, cells(*block))
            yield found

        total: dict = {}
        for found in self.blocks.mapPartitions(task).collect():
            add(total, found.items())
        return total

    def answer(self, objective, requests: list[tuple[np.ndarray, list[tuple[int, int]], bool]]) -> list[tuple[float | None, list[np.ndarray]]]:
        """(value or None, subgradients) of every request."""
        joined: dict[bytes, list] = {}
        for v, spans, valued in requests:
            known = joined.setdefault(v.tobytes(), [v, set(), False])
            known[1].update(spans)
            known[2] |= valued
        asked = [(key, v, sorted(spans), valued) for key, (v, spans, valued) in joined.items()]

        def cells(ids, y, x):
            for at, (_, v, spans, valued) in enumerate(asked):
                if valued:
                    yield (at, None), objective.rows_value(x @ v, y)
                edges = np.searchsorted(ids, [(lo, hi + 1) for lo, hi in spans]) if spans else ()
                for span, (a, b) in zip(spans, edges, strict=True):
                    if a < b:
                        yield (at, span), objective.part(x[a:b], y[a:b], v)

        found, place = self._sums(cells), {key: at for at, (key, *_) in enumerate(asked)}
        out = []
        for v, spans, valued in requests:
            at, zero = place[v.tobytes()], np.zeros_like(v)
            out.append((found.get((at, None), 0.0) + objective.regulariser(v) if valued else None, [found.get((at, span), zero) for span in spans]))
        return out

    def parts(self, objective, tasks, v):
        return self.answer(objective, [(v, list(tasks), False)])[0][1]

    def value(self, objective, v: np.ndarray) -> float:
        return self.answer(objective, [(v, [], True)])[0][0]

    def optimum(self, objective) -> float:
        """Newton's method, one job a step."""
        v = objective.start()
        for _ in range(60):

            def cells(ids, y, x, v=v):
                z = x @ v
                yield "grad", x.T @ objective.pull(z, y)
                yield "hess", (x * objective.curvature(z, y)[:, None]).T @ x

            found = self._sums(cells)
            step = np.linalg.solve(found["hess"] + objective.lam * np.eye(len(self.cols)), found["grad"] + objective.regulariser_grad(v))
            v = v - step
            if np.abs(step).max() < 1e-12:
                break
        return self.value(objective, v)


def _cell(i: int, c: int, k: int) -> str:
    return f"g{i}" if k == 1 else f"g{i}_{c}"


def _batch_products(nz: pa.Array, v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(column numbers, owning row of each, products with v) of a batch of sparse binary rows."""
    cols = nz.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
    sizes = nz.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
    owner = np.repeat(np.arange(len(sizes)), sizes)
    return cols, owner, np.stack([np.bincount(owner, weights=v[cols, c], minlength=len(sizes)) for c in range(v.shape[1])], axis=1)


class ArrowKernel:
    """Subgradients of sparse binary rows (sample_idx, nz, and label if the objective has one) by batches."""

    def __init__(self, matrix: DataFrame, d: int, n: int | None = None):
        self.matrix, self.d, self.n = matrix, d, matrix.count() if n is None else n

    def _rows(self, *names: str) -> DataFrame:
        label = F.col("label").cast("double") if "label" in self.matrix.columns else F.lit(0.0)
        return self.matrix.select(*names, "nz", label.alias("label"))

    def parts(self, objective, tasks, v):
        lows = np.array([lo for lo, _ in tasks])
        order = np.argsort(lows)
        highs = np.array([hi for _, hi in tasks])[order]
        lows = lows[order]
        shared = self.matrix.sparkSession.sparkContext.broadcast(v)
        d, k = self.d, v.shape[1]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums: dict[int, np.ndarray] = {}
            for batch in batches:
                index = batch.column("sample_idx").to_numpy()
                cols, owner, z = _batch_products(batch.column("nz"), shared.value)
                pull = objective.pull(z, batch.column("label").to_numpy())
                at = np.searchsorted(lows, index, side="right") - 1
                at[(at >= 0) & (index > highs[np.maximum(at, 0)])] = -1
                for j in np.unique(at[at >= 0]).tolist():
                    mine = at[owner] == j
                    grad = sums.setdefault(j, np.zeros((d, k)))
                    for c in range(k):
                        grad[:, c] += np.bincount(cols[mine], weights=pull[owner[mine], c], minlength=d)
            if sums:
                yield pa.RecordBatch.from_arrays([pa.array([int(lows[j]) for j in sums], pa.int64()), pa.array([g.ravel() for g in sums.values()], pa.list_(pa.float64()))], names=["lo", "grad"])

        partial = self._rows("sample_idx").where(_ranges(tasks)).mapInArrow(run, "lo long, grad array<double>")
        found = {r["lo"]: np.array(r["total"]).reshape(d, k) for r in partial.groupBy("lo").agg(vector_sum("grad").alias("total")).collect()}
        shared.unpersist()
        return [found.get(lo, np.zeros((d, k))) for lo, _ in tasks]

    def value(self, objective, v):
        shared = self.matrix.sparkSession.sparkContext.broadcast(v)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                _, _, z = _batch_products(batch.column("nz"), shared.value)
                yield pa.RecordBatch.from_arrays([pa.array([float(objective.row_values(z, batch.column("label").to_numpy()).sum())])], names=["s"])

        total = self._rows().mapInArrow(run, "s double").agg(F.sum("s")).first()[0]
        return (total or 0.0) + objective.regulariser(v)

    def optimum(self, objective, extra: int = 5, steps: int = 200) -> float:
        """Subspace iteration with some further columns, one distributed job a step, until the value stands still."""
        v = gram_schmidt(np.array([[uniform_np("optimum", i, c) - 0.5 for c in range(objective.k + extra)] for i in range(self.d)]))
        best = 0.0
        for _ in range(steps):
            y = -self.parts(objective, [(1, self.n)], v)[0]
            values, turn = np.linalg.eigh(v.T @ y)
            now = -float(np.sort(values)[::-1][: objective.k].sum()) / objective.norm
            v = gram_schmidt(y @ turn[:, ::-1])
            if abs(now - best) < 1e-13:
                break
            best = now
        return now


def choose_kernel(d: int, density: float, n: int, limit: int | None = None) -> str:
    """``local`` behind the size check, expressions for few dense columns, batches otherwise."""
    if n * d * 8 <= (LOCAL_LIMIT_BYTES if limit is None else limit):
        return "local"
    return "expression" if d <= 64 and density > 0.3 else "arrow"
