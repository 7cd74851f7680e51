"""Further problems, wall-clock mode and small helpers."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from stalegrad.operators import gradients as G
from stalegrad.operators import latency as L
from stalegrad.operators import matrix as M
from stalegrad.operators import partitioning as P
from stalegrad.functions.aggregates import gram_sum, interval_rows, vector_sum
from stalegrad.operators.objectives import PCA, LeastSquares, Logistic, distributed_gram_schmidt, gram_schmidt
from stalegrad.operators.simulate import predict_independent_iterations
from stalegrad.plans import wallclock, workloads
from stalegrad.plans.balancer import Balancer
from stalegrad.plans.loop import Options, gamma_latency, optimise
from stalegrad.sources.tables import load


@pytest.mark.parametrize("kind", ["null", "quality", "vectors"])
def test_other_logistic_problems_converge(spark, sf, kind):
    kernel, o, best = workloads.labelled_problem(spark, sf, kind)
    out = optimise(kernel, o, 4, gamma_latency(workloads.stats_of(spark, sf, 4)), Options(w=2, parts=5, iterations=150), best, every=10)
    assert 0 <= out["gap"].iloc[-1] < 0.2 * out["gap"].iloc[0] and out["coverage"].iloc[-1] == 1.0


def test_wall_clock_run(spark, sf):
    m = M.logit_matrix(load(spark, sf, "lineitem"), load(spark, sf, "part"))
    local = G.local_logistic(m)
    o = Logistic(local.n, 7)
    out, trace = wallclock.run(local, o, local.n, 4, 2, 40, parts=4)
    assert len(out) == 40 and (out["n_fresh"] >= 2).all() and out["objective"].iloc[-1] < 0.68
    assert set(trace["worker"]) <= {1, 2, 3, 4} and (trace["round_trip_ms"] >= trace["comp_ms"]).all()
    far, _ = wallclock.run(G.ExpressionKernel(m, local.n), o, local.n, 2, 1, 2, parts=2)
    assert len(far) == 2


def test_release_and_cloud(spark, sf):
    f = workloads.release_script(50, 40, 49)
    assert f(44, 3, 500.0) == 1 + 0.4 * 45 / 50 and f(44, 3, 1500.0) == 1.0 and f(9, 3, 1500.0) == 1 + 0.4 * 10 / 50
    stats = workloads.cloud_stats(spark, sf, 10)
    assert np.allclose(stats["e_comm"], workloads.stats_of(spark, sf, 10)["e_comm"] * 10)


def test_helpers(spark, sf):
    events = load(spark, sf, "events")
    share = M.hash_sample(events, 0.3, 1)
    assert 200 < share.count() < 400 and share.exceptAll(M.hash_sample(events.repartition(7), 0.3, 1)).count() == 0
    assert M.coded_load(45.0, 45, 49) == 49.0 and M.comm_bytes(2504, 3) == 30_048 and M.comp_load(10, 4, 2, 0.5) == 80
    assert predict_independent_iterations(2.0, 3).tolist() == [2.0, 4.0, 6.0]
    layout = P.worker_layout(spark, 100, 4)
    both = workloads.layout_profiles(layout, L.worker_stats(L.trace_from_events(events, 5)))
    assert both.count() == 5 and both.where("rows IS NULL").count() == 1
    frozen = Balancer(np.full(3, 10), np.full(3, 2), 2, freeze_from=0)
    assert frozen.counts(5, 1.0, [2, 2, 2]) == [2, 2, 2]
    v = M.indicator_matrix(spark.createDataFrame([(1, "b"), (1, "a"), (2, "b")], "r int, c string"), "r", "c")
    assert {r.r: r.nz for r in v.collect()} == {1: [1, 2], 2: [2]}


def test_slow_ramp_release(spark, sf):
    stats = L.worker_stats(L.trace_from_events(load(spark, sf, "events"), 8))
    a = L.slow_ramp(stats, 8, release=F.col("worker") >= 7).join(stats.select("worker", F.col("e_comp").alias("e")), "worker")
    assert a.where("worker >= 7 AND e_comp <> e").count() == 0 and a.where("worker < 7 AND e_comp <= e").count() == 0


@pytest.mark.parametrize("kind", ["logistic", "pca"])
def test_runs_above_the_size_check_stay_in_spark(spark, sf, kind):
    """The same trajectory from the distributed kernels as from the matrix in one process."""
    configs = [("stale_cache", 3, False), ("gd", 4, False)]
    cols = ["run_id", "t", "time_ms", "objective", "gap", "coverage", "cache_entries", "n_fresh", "n_stale"]
    near, far = (workloads.sweep(spark, sf, kind, configs, workers=4, iterations=6, seeds=1, every=3, limit=limit).select(*cols).orderBy("run_id", "t").toPandas() for limit in (None, 0))
    assert len(near) == 6 and np.allclose(near.to_numpy(float), far.to_numpy(float), rtol=1e-7, atol=1e-9)


def test_expression_kernel_takes_the_objective(spark):
    rng = np.random.default_rng(2)
    x, y = rng.normal(size=(40, 3)), rng.normal(size=40)
    matrix = spark.createDataFrame([(i + 1, float(y[i]), *map(float, x[i])) for i in range(40)], "sample_idx long, label double, x0 double, x1 double, x2 double")
    kernel, v1, v2 = G.ExpressionKernel(matrix, 40), rng.normal(size=(3, 1)), rng.normal(size=(3, 2))
    for objective, v in ((LeastSquares(40, 3, 0.1), v1), (Logistic(40, 3), v1), (PCA(40, 3, 2, 5.0), v2)):
        local = G.LocalKernel(x, y)
        for a, b in zip(kernel.parts(objective, [(1, 15), (20, 40)], v), local.parts(objective, [(1, 15), (20, 40)], v), strict=True):
            assert np.allclose(a, b)
        assert np.isclose(kernel.value(objective, v), local.value(objective, v))
    assert np.isclose(kernel.optimum(LeastSquares(40, 3, 0.1)), LeastSquares(40, 3, 0.1).optimum(x, y))


def test_distributed_gram_schmidt(spark):
    v = np.random.default_rng(3).normal(size=(30, 3))
    rows = spark.createDataFrame([(i, v[i].tolist()) for i in range(30)], "col int, v array<double>")
    got = np.array([r["v"] for r in distributed_gram_schmidt(rows, 3).orderBy("col").collect()])
    assert np.allclose(got, gram_schmidt(v))


def test_grouped_aggregates(spark):
    rows = spark.createDataFrame([(1, [1.0, 2.0], 1, 5), (1, [3.0, 4.0], 4, 9), (2, [1.0, 1.0], 20, 20), (2, None, 3, 3)], "g int, v array<double>, lo long, hi long")
    got = {r.g: (r.s, r.q, r.n) for r in rows.groupBy("g").agg(vector_sum("v").alias("s"), gram_sum("v").alias("q"), interval_rows("lo", "hi").alias("n")).collect()}
    assert got == {1: ([4.0, 6.0], [10.0, 14.0, 14.0, 20.0], 9), 2: ([1.0, 1.0], [1.0, 1.0, 1.0, 1.0], 2)}
