"""The experiments on the given tables: problems, latencies, sweeps and ablations.

Small matrices (checked size) are collected once, and the runs of a sweep are
spread over executors, one group a run; larger ones stay distributed and the
runs go side by side, one job answering what all of them ask for next.
"""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stalegrad.operators import gradients as G
from stalegrad.operators import latency as L
from stalegrad.operators import matrix as M
from stalegrad.operators import metrics
from stalegrad.operators import order_stats as O
from stalegrad.operators.objectives import PCA, Logistic
from stalegrad.operators.partitioning import sub_bounds
from stalegrad.plans.balancer import Balancer, Simulator, baseline_bound, imbalance, rebalance
from stalegrad.plans.loop import Options, coded_bound, delivery_log, gamma_latency, optimise, plan, run, steps, together
from stalegrad.sources.tables import load

#: Steps and piece counts of the two problems.
ETA = {"pca": 0.9, "logistic": 0.25}
PARTS = 10
RAMP = 0.4
TRAJECTORY = "run_id int, method string, w int, balanced boolean, t int, time_ms double, objective double, gap double, coverage double, cache_entries int, n_fresh int, n_stale int"


def stats_of(spark: SparkSession, d: str, workers: int, ramp: float = RAMP, base_ms: float = 1000.0) -> pd.DataFrame:
    """Moments of every worker (one row a worker) from the events table."""
    return L.worker_stats(L.trace_from_events(load(spark, d, "events"), workers, base_ms, ramp)).orderBy("worker").toPandas()


def problem(spark: SparkSession, d: str, kind: str, columns: int = 512, limit: int | None = None, optimum: bool = True):
    """(kernel, objective, optimum, 0 if not wanted): in one process behind the size check, else by the kernel that fits the matrix."""
    limit = G.LOCAL_LIMIT_BYTES if limit is None else limit
    if kind == "logistic":
        matrix = M.logit_matrix(load(spark, d, "lineitem"), load(spark, d, "part"))
        n, width, share = matrix.count(), len(G.dense_columns(matrix)), 1.0
        objective = Logistic(n, width)
    else:
        matrix = M.token_matrix(spark.read.parquet(f"{d}/documents.parquet"), columns)
        n, filled = matrix.agg(F.count(F.lit(1)), F.sum(F.size("nz"))).first()
        width, share = columns, (filled or 0) / max(1, n * columns)
        objective = PCA(n, columns, 3, float(filled or 0))
    choice = G.choose_kernel(width, share, n, limit)
    if choice == "local":
        kernel = G.local_logistic(matrix) if kind == "logistic" else G.local_sparse(matrix, columns)
        return kernel, objective, objective.optimum(kernel.x, kernel.y) if optimum else 0.0
    kernel = G.BlockKernel(matrix, n) if kind == "logistic" else G.ArrowKernel(matrix, columns, n)
    return kernel, objective, kernel.optimum(objective) if optimum else 0.0


def labelled_problem(spark: SparkSession, d: str, kind: str):
    """The further logistic problems: ``null`` (labels without signal), ``quality`` and ``vectors``."""
    if kind == "null":
        matrix = M.logit_matrix(load(spark, d, "lineitem"), load(spark, d, "part"), null_label=True)
    elif kind == "quality":
        matrix = M.document_matrix(spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet"))
    else:
        matrix = M.embedding_matrix(load(spark, d, "embeddings"))
    kernel = G.local_logistic(matrix)
    objective = Logistic(kernel.n, kernel.x.shape[1])
    return kernel, objective, objective.optimum(kernel.x, kernel.y)


def release_script(workers: int, first: int, last: int, after_ms: float = 1000.0, amount: float = RAMP):
    """The ramp, off again for workers first..last after a time."""

    def factor(i: int, t: int, now: float) -> float:
        released = first <= i + 1 <= last and now >= after_ms
        return 1.0 if released else 1 + amount * (i + 1) / workers

    return factor


def cloud_stats(spark: SparkSession, d: str, workers: int = 100, noise: float = 10.0) -> pd.DataFrame:
    """Many workers with noisy communication: its moments enlarged by ``noise``."""
    stats = stats_of(spark, d, workers)
    return stats.assign(e_comm=stats["e_comm"] * noise, v_comm=stats["v_comm"].fillna(0) * noise**2, v_comp=stats["v_comp"].fillna(0))


def layout_profiles(layout: DataFrame, stats: DataFrame) -> DataFrame:
    """Layout and moments of each worker side by side, in cogrouped batches; a missing side leaves nulls."""

    def join(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        a, b = (left if len(left) else None), (right if len(right) else None)
        worker = (a if a is not None else b)["worker"].iloc[0]
        return pd.DataFrame({"worker": [worker], "rows": [a["rows"].iloc[0] if a is not None else None], "e_total": [float(b["e_comm"].iloc[0] + b["e_comp"].iloc[0]) if b is not None else None]})

    return layout.groupBy("worker").cogroup(stats.groupBy("worker")).applyInPandas(join, "worker int, rows long, e_total double")


def ablations(spark: SparkSession, d: str, kind: str = "logistic", workers: int = 8, w: int = 3, iterations: int = 150) -> DataFrame:
    """Least gap reached by the stale-cache method under each option."""
    variants = {
        "default": {}, "no_margin": {"margin": 0.0}, "wide_margin": {"margin": 0.2}, "no_late_results": {"use_late": False},
        "unscaled": {"scale_by_coverage": False}, "random_order": {"order": "random"}, "endpoint_overlap": {"overlap": "endpoint"},
    }
    configs = [("stale_cache", w, False, options) for options in variants.values()]
    best = sweep(spark, d, kind, configs, workers, iterations, 1, 5).groupBy("run_id").agg(F.min("gap").alias("least_gap"), F.max("time_ms").alias("time_ms"), F.max("coverage").alias("coverage"))
    named = F.element_at(F.array(*[F.lit(name) for name in variants]), F.col("run_id") + 1)
    return best.orderBy("run_id").select(named.alias("variant"), "least_gap", "time_ms", "coverage")


def gd_steps(matrix: DataFrame, eta: float, steps: int) -> list[tuple[int, np.ndarray, float]]:
    """(t, iterate, mean loss) of plain gradient descent by the expression kernel."""
    n = matrix.count()
    kernel, objective = G.ExpressionKernel(matrix, n), Logistic(n, len(G.dense_columns(matrix)))
    v, out = objective.start(), []
    for t in range(steps + 1):
        out.append((t, v, kernel.value(objective, v) - objective.regulariser(v)))
        v = v - eta * (kernel.parts(objective, [(1, n)], v)[0] + objective.regulariser_grad(v))
    return out


def sweep(spark: SparkSession, d: str, kind: str, configs: list[tuple], workers: int = 8, iterations: int = 200, seeds: int = 5, every: int = 5, options: dict | None = None, stats: pd.DataFrame | None = None, script=None, limit: int | None = None, solve_delay: float = 500.0) -> DataFrame:
    """Trajectories of (method, w, balanced, and options of its own if there are any) x seeds.

    A small matrix travels to the tasks and every run is a task of its own.  A
    matrix above ``limit`` bytes stays distributed: the runs are planned in tasks
    and then go side by side, one job over the matrix for each step of all runs.
    """
    kernel, objective, optimum = problem(spark, d, kind, limit=limit)
    stats = stats_of(spark, d, workers) if stats is None else stats
    extra = dict(options or {})
    runs = [(method, int(w), bool(balanced), seed, own) for method, w, balanced, *own in configs for seed in range(seeds)]
    n = kernel.n

    def planned(run_id: int, stats: pd.DataFrame):
        method, w, balanced, seed, own = runs[run_id]
        o = Options(method=method, w=w, iterations=iterations, eta=1.0 if method == "gd" else ETA[kind], seed=seed, **({"parts": PARTS} | extra | (own[0] if own else {})))
        balancer = None
        if balanced:
            rows = np.array([b - a + 1 for a, b in (sub_bounds(n, workers, i + 1) for i in range(workers))])
            balancer = Balancer(rows, np.full(workers, o.parts), w, solve_delay=solve_delay)
        return o, plan(n, workers, gamma_latency(stats, seed, script), o, balancer)

    def labelled(run_id: int, out: pd.DataFrame) -> pd.DataFrame:
        method, w, balanced, *_ = runs[run_id]
        return out.assign(run_id=run_id, method=method, w=w, balanced=balanced)[[c.split()[0] for c in TRAJECTORY.split(", ")]]

    if not isinstance(kernel, G.LocalKernel):
        plans = spark.sparkContext.parallelize(range(len(runs)), max(1, len(runs))).map(lambda run_id: planned(run_id, stats)).collect()
        if isinstance(kernel, G.BlockKernel):
            found = together(kernel, objective, [steps(n, objective, schedule, o, optimum, every) for o, schedule in plans])
            kernel.close()
        else:
            with ThreadPoolExecutor(4) as pool:
                found = list(pool.map(lambda p: run(kernel, objective, p[1], p[0], optimum, every), plans))
        return spark.createDataFrame(pd.concat([labelled(i, out) for i, out in enumerate(found)]), TRAJECTORY)
    shared = spark.sparkContext.broadcast((kernel.x, kernel.y, objective, optimum, stats))

    def task(pdf: pd.DataFrame) -> pd.DataFrame:
        x, y, objective, optimum, stats = shared.value
        run_id = int(pdf["run_id"].iloc[0])
        o, schedule = planned(run_id, stats)
        return labelled(run_id, run(G.LocalKernel(x, y), objective, schedule, o, optimum, every))

    table = spark.createDataFrame([(i,) for i in range(len(runs))], "run_id int").repartition(max(1, len(runs)), "run_id")
    return table.groupBy("run_id").applyInPandas(task, TRAJECTORY)


def comparison(spark: SparkSession, d: str, kind: str, workers: int, quorum: int, iterations: int = 600, seeds: int = 1) -> DataFrame:
    """Time to each gap of the stale-cache method and its baselines."""
    configs = [("stale_cache", quorum, False), ("avg_gradient", workers, False), ("avg_gradient", quorum, False), ("sgd", quorum, False), ("gd", workers, False)]
    runs = sweep(spark, d, kind, configs, workers, iterations, seeds)
    return metrics.time_to_gap(runs, [1e-2, 1e-4, 1e-6, 1e-8], ["method", "w", "balanced"])


def release_comparison(spark: SparkSession, d: str, kind: str = "logistic", workers: int = 49, quorums: tuple[int, ...] = (10,), iterations: int = 400, seeds: int = 5) -> DataFrame:
    """Times to each gap when the slowest ten workers come back to speed after one second of the run."""
    stats = stats_of(spark, d, workers, ramp=0.0)
    script = release_script(workers, max(1, workers - 9), workers)
    configs = [("stale_cache", w, False) for w in quorums] + [("avg_gradient", workers, False), ("sgd", quorums[0], False), ("gd", workers, False)]
    runs = sweep(spark, d, kind, configs, workers, iterations, seeds, stats=stats, script=script)
    return metrics.time_to_gap(runs, [1e-2, 1e-4, 1e-6, 1e-8], ["method", "w", "balanced", "run_id"]).groupBy("method", "w", "balanced", "eps").agg(F.avg("time_ms").alias("time_ms"), F.count("time_ms").alias("reached"))


def cloud_comparison(spark: SparkSession, d: str, kind: str = "logistic", workers: int = 100, quorums: tuple[int, ...] = (5, 10, 20), iterations: int = 400, seeds: int = 5, balanced: bool = True) -> DataFrame:
    """Times to each gap with many workers and noisy communication, with the balancer for the widest quorum."""
    stats = cloud_stats(spark, d, workers)
    configs = [("stale_cache", w, False) for w in quorums] + [("avg_gradient", workers, False), ("gd", workers, False)] + ([("stale_cache", quorums[-1], True)] if balanced else [])
    runs = sweep(spark, d, kind, configs, workers, iterations, seeds, stats=stats, solve_delay=60_000.0)
    return metrics.time_to_gap(runs, [1e-2, 1e-4, 1e-6, 1e-8], ["method", "w", "balanced", "run_id"]).groupBy("method", "w", "balanced", "eps").agg(F.avg("time_ms").alias("time_ms"), F.count("time_ms").alias("reached"))


def balancing_ablations(spark: SparkSession, d: str, workers: int = 8, w: int = 4, iterations: int = 140, parts: int = 100) -> DataFrame:
    """Latency and cache health under the speed script for each gate, overshoot and way of aligning."""
    stats = stats_of(spark, d, workers, ramp=0.0)
    n = load(spark, d, "lineitem").count()
    rows = np.array([b - a + 1 for a, b in (sub_bounds(n, workers, i + 1) for i in range(workers))])
    variants = [(g, "walk", "undo_last") for g in (0.0, 0.1, float("inf"))] + [(0.0, mode, "undo_last") for mode in ("nearest", "restart", "none")] + [(0.1, "walk", "keep")]

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        gate, mode, overshoot = pdf.iloc[0][["gate", "align_mode", "overshoot"]]
        balancer = Balancer(rows, np.full(workers, parts), w, threshold=gate, solve_delay=10_000.0, overshoot=overshoot)
        p = plan(n, workers, gamma_latency(stats, 3, balancing_script()), Options(w=w, iterations=iterations, parts=parts, align_mode=mode), balancer)
        out = (gate, mode, overshoot, float(p.ends[-1]), sum(len(x) for t in p.evicted for x in t), int(sum(n - c for c in p.covered)), sum(e["distributed"] for e in balancer.events))
        return pd.DataFrame([out], columns=["gate", "align_mode", "overshoot", "end_ms", "evicted", "missing_row_iterations", "published"])

    table = spark.createDataFrame([(i, *v) for i, v in enumerate(variants)], "variant int, gate double, align_mode string, overshoot string").repartition(len(variants), "variant")
    return table.groupBy("variant").applyInPandas(one, "gate double, align_mode string, overshoot string, end_ms double, evicted long, missing_row_iterations long, published long")


def spark_logistic(spark: SparkSession, d: str, workers: int = 8, w: int = 3, iterations: int = 40, method: str = "stale_cache") -> DataFrame:
    """A run whose matrix stays distributed: one job an iteration over the row ranges it needs."""
    matrix = M.logit_matrix(load(spark, d, "lineitem"), load(spark, d, "part"))
    n = matrix.count()
    objective = Logistic(n, len(G.dense_columns(matrix)))
    o = Options(method=method, w=w, iterations=iterations, parts=PARTS, eta=ETA["logistic"])
    out = optimise(G.ExpressionKernel(matrix, n), objective, workers, gamma_latency(stats_of(spark, d, workers)), o, every=max(1, iterations // 5))
    return spark.createDataFrame(out.drop(columns="gap"), "t int, time_ms double, objective double, coverage double, cache_entries int, n_fresh int, n_stale int")


def block_latencies(stats: pd.DataFrame, iterations: int, parts: int = PARTS, seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """(iteration, worker) communication and whole-block computation."""
    draw = gamma_latency(stats, seed, count=iterations)
    cells = [[draw(i, t, t, 0.0) for i in range(len(stats))] for t in range(iterations)]
    x = np.array(cells)
    return x[:, :, 0], x[:, :, 1] * parts


def coded_run(spark: SparkSession, d: str, num: int, den: int, workers: int = 8, iterations: int = 100) -> DataFrame:
    """Gradient descent's convergence with the latency of ideal coding."""
    kernel, objective, optimum = problem(spark, d, "logistic")
    stats = stats_of(spark, d, workers)
    gd = optimise(kernel, objective, workers, gamma_latency(stats), Options(method="gd", w=workers, iterations=iterations, parts=PARTS, eta=1.0), optimum)
    return spark.createDataFrame(coded_bound(gd, *block_latencies(stats, iterations), num, den), "t int, time_ms double, objective double, gap double")


def rebalanced(spark: SparkSession, d: str, workers: int = 8, w: int = 4, parts: int = 100) -> DataFrame:
    """Counts of the balancer under the ramp, with the imbalance before and after."""
    stats = stats_of(spark, d, workers)
    n = load(spark, d, "lineitem").count()
    rows = np.array([b - a + 1 for a, b in (sub_bounds(n, workers, i + 1) for i in range(workers))])
    old, sim = np.full(workers, parts), Simulator(w)
    h_min = baseline_bound(stats, rows, old, old, sim)
    new = rebalance(stats, rows, old, h_min, sim, overshoot="undo_last")
    ec, ep = stats["e_comm"].to_numpy(), stats["e_comp"].to_numpy()
    a, b = imbalance(ec, ep), imbalance(ec, ep * old / new)
    return spark.createDataFrame([(i + 1, parts, int(p), float(h_min), a, b) for i, p in enumerate(new)], "worker int, parts_old int, parts_new int, h_min double, ratio_old double, ratio_new double")


def balancing_script(slowed: tuple[int, ...] = (0, 2, 5), sped: tuple[int, ...] = (1, 2, 6)):
    """Three workers slow down at iteration 40, three speed up at 90."""

    def factor(i: int, t: int, now: float) -> float:
        return (2.0 if i in slowed and t >= 40 else 1.0) * (0.6 if i in sped and t >= 90 else 1.0)

    return factor


def scripted_balancing(spark: SparkSession, d: str, workers: int = 8, iterations: int = 140, parts: int = 100) -> DataFrame:
    """Iteration ends with and without the balancer while workers change speed (every worker is waited for)."""
    stats = stats_of(spark, d, workers, ramp=0.0)
    n = load(spark, d, "lineitem").count()
    rows = np.array([b - a + 1 for a, b in (sub_bounds(n, workers, i + 1) for i in range(workers))])
    o = Options(method="stale_cache", w=workers, iterations=iterations, parts=parts)
    out = []
    for balanced in (False, True):
        balancer = Balancer(rows, np.full(workers, parts), workers, solve_delay=2000.0) if balanced else None
        p = plan(n, workers, gamma_latency(stats, 3, balancing_script()), o, balancer)
        out += [(balanced, t + 1, float(e), int(min(p.parts[t])), int(max(p.parts[t]))) for t, e in enumerate(p.ends)]
    return spark.createDataFrame(out, "balanced boolean, t int, end_ms double, least_parts int, most_parts int")


def order_stat_models(spark: SparkSession, d: str, workers: int = 8, count: int = 2048) -> DataFrame:
    """Measured and predicted order statistics under the ramp, and the relative error of each model."""
    trace = L.trace_from_events(load(spark, d, "events"), workers, 1000.0, RAMP)
    seen, stats = O.empirical_order_stats(trace, workers), L.worker_stats(trace)
    out = seen.select("w", F.col("mean_ms").alias("measured"))
    for model in ("gamma", "iid_gamma", "iid_shifted_exp"):
        got = O.predict_order_stats(spark, stats, count, 1, model).select("w", F.col("mean_ms").alias(model))
        out = out.join(got, "w")
    return out.select("*", *[(F.abs(F.col(m) - F.col("measured")) / F.col("measured")).alias(f"error_{m}") for m in ("gamma", "iid_gamma", "iid_shifted_exp")])


def delivery_rows(spark: SparkSession, d: str, workers: int = 8, w: int = 3, iterations: int = 60) -> DataFrame:
    """The delivery log of a balanced run with the cache action of every arrival."""
    n = load(spark, d, "lineitem").count()
    rows = np.array([b - a + 1 for a, b in (sub_bounds(n, workers, i + 1) for i in range(workers))])
    balancer = Balancer(rows, np.full(workers, PARTS), w, threshold=0.0, solve_delay=5000.0)
    p = plan(n, workers, gamma_latency(stats_of(spark, d, workers)), Options(w=w, iterations=iterations, parts=PARTS), balancer)
    return spark.createDataFrame(delivery_log(p))
