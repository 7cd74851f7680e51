"""Restart of a long run, freezing, in-place renewal, streamed steps and the wider SQL surface."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from stalegrad.functions.draws import gamma_cdf, gamma_quantile, normal_quantile
from stalegrad.functions.sqlfuncs import register
from stalegrad.operators import gradients as G
from stalegrad.operators import matrix as M
from stalegrad.operators.cache import IntervalCache
from stalegrad.operators.objectives import PCA, Logistic
from stalegrad.plans import loop, workloads
from stalegrad.plans.balancer import Balancer
from stalegrad.plans.restart import RunStore
from stalegrad.sources import tables
from stalegrad.streaming import profile as S

RNG = np.random.default_rng(11)


def small(n=400, d=4):
    x = RNG.normal(size=(n, d))
    y = np.where(x[:, 0] + RNG.normal(size=n) > 0, 1.0, -1.0)
    o = Logistic(n, d)
    return G.LocalKernel(x, y), o, o.optimum(x, y)


def latency(workers=5):
    return loop.trace_latency(RNG.gamma(2, 1, (50, workers)), RNG.gamma(2, 5, (50, workers)) * (1 + np.arange(workers) / workers))


def test_a_run_goes_on_from_its_snapshot(spark, tmp_path):
    kernel, o, best = small()
    options = loop.Options(w=2, iterations=23, parts=4)
    schedule = loop.plan(400, 5, latency(), options)
    whole = loop.run(kernel, o, schedule, options, best)
    store = RunStore(spark, str(tmp_path / "run"), every=5)
    cut = loop.Plan(*(x[:12] for x in (schedule.ends, schedule.arrivals, schedule.actions, schedule.evicted, schedule.covered, schedule.parts)))
    loop.run(kernel, o, cut, options, best, store=store)  # the driver is lost after 12 iterations
    (tmp_path / "run" / "t=000000099").mkdir()  # a snapshot that was never finished
    assert store.load()[0] == 10
    again = loop.run(kernel, o, schedule, options, best, store=store)
    assert again["t"].min() == 11
    both = whole.merge(again, on="t")
    assert len(both) == 13 and np.allclose(both["gap_x"], both["gap_y"], atol=1e-12) and (both["cache_entries_x"] == both["cache_entries_y"]).all()


def test_an_equal_interval_is_renewed_in_place():
    cache = IntervalCache()
    for lo in (1, 11, 21):
        cache.offer(lo, lo + 9, 1, np.full((1, 1), float(lo)))
    entry, starts = cache.entries[1], cache.starts
    event = cache.offer(11, 20, 3, np.full((1, 1), 5.0))
    assert event.action == "replace" and event.evicted == [(11, 20, 1)] and cache.entries[1] is entry and cache.starts is starts
    assert cache.total[0, 0] == 1 + 5 + 21 and cache.rows == 30
    assert cache.offer(11, 20, 3).action == "reject"


def test_balancing_is_frozen_below_a_gap():
    kernel, o, best = small()
    rows = np.full(5, 80)
    made = []

    def balancer(freeze):
        made.append(Balancer(rows, np.full(5, 4), 2, threshold=0.0, solve_delay=1.0, freeze_from=freeze))
        return made[-1]

    out = loop.optimise_frozen(kernel, o, 5, latency(), loop.Options(w=2, iterations=60, parts=4), best, balancer, 1e-2)
    assert made[1].freeze_from is not None and all(e["t"] < made[1].freeze_from for e in made[1].events) and len(out) == 61


def test_textbook_average_converges():
    kernel, o, best = small()
    out = loop.textbook_average(kernel, o, 10, latency(), 400, 0.25, best, every=50)
    assert out["gap"].iloc[-1] < 1e-6 and out["coverage"].iloc[-1] == 1


def test_streamed_steps_equal_the_batch_loop(spark, tmp_path):
    rows = [(1 + 10 * i, 10 + 10 * i, [float(i), 1.0]) for i in range(4)]
    for i, r in enumerate(rows):
        spark.createDataFrame([r], "lo long, hi long, grad array<double>").coalesce(1).write.parquet(str(tmp_path / "in" / f"{i}"))
    stream = spark.readStream.schema("lo long, hi long, grad array<double>").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in" / "*"))
    seen = []
    v = S.step_each_batch(stream, np.zeros((2, 1)), 0.1, 40, str(tmp_path / "c"), lambda number, v: seen.append(number))
    assert np.allclose(v[:, 0], [-0.1 * 4 * 6, -0.1 * 4 * 4]) and len(seen) == 4


@pytest.mark.parametrize("mode", ["complete", "update"])
def test_output_modes(spark, tmp_path, mode):
    spark.range(20).select((F.col("id") % 3).alias("worker")).write.parquet(str(tmp_path / "in"))
    counted = spark.readStream.schema("worker long").parquet(str(tmp_path / "in")).groupBy("worker").count()
    if mode == "complete":
        S.into_table(counted, "counted", "complete", str(tmp_path / "c"))
        assert {(r.worker, r["count"]) for r in spark.table("counted").collect()} == {(0, 7), (1, 7), (2, 6)}
    else:
        got = []
        counted.writeStream.outputMode("update").foreachBatch(lambda b, i: got.extend(b.collect())).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start().awaitTermination()
        assert {(r.worker, r["count"]) for r in got} == {(0, 7), (1, 7), (2, 6)}


def test_quantiles_and_sql_functions(spark, sf):
    u = np.array([0.01, 0.3, 0.5, 0.999])
    for shape in (0.4, 1.0, 25.0):
        assert np.allclose(gamma_cdf(gamma_quantile(u, shape, 2.0), shape, 2.0), u, atol=1e-9)
    assert abs(normal_quantile(np.array([0.975]))[0] - 1.959964) < 1e-5
    register(spark, sf)
    assert spark.sql("SELECT align_piece(10, 2, 4, 1) AS k").first()["k"] == 3
    ends = spark.sql("SELECT * FROM simulate(array(10D, 12D, 20D), array(1D, 2D, 3D), 2, 8, 0.0D, 5)").collect()
    assert len(ends) == 8 and all(a["end_ms"] < b["end_ms"] for a, b in zip(ends, ends[1:])) and min(r["n_fresh"] for r in ends) >= 2
    assert spark.sql("SELECT vector_sum(v) AS s FROM VALUES (array(1D, 2D)), (array(3D, 4D)) AS t(v)").first()["s"] == [4.0, 6.0]
    assert abs(spark.sql("SELECT gamma_quantile(0.5D, 1D, 1D) AS x").first()["x"] - np.log(2)) < 1e-9


def test_indicator_columns_are_numbered_by_value(spark):
    pairs = spark.createDataFrame([(r, f"c{(r * 7 + j) % 90:02d}") for r in range(60) for j in range(3)], "r int, c string")
    names = {c: i + 1 for i, c in enumerate(sorted({x.c for x in pairs.collect()}))}
    got = {x.r: x.nz for x in M.indicator_matrix(pairs, "r", "c").collect()}
    assert got == {r: sorted({names[f"c{(r * 7 + j) % 90:02d}"] for j in range(3)}) for r in range(60)}


def test_logs_are_appended(spark, tmp_path):
    log = spark.createDataFrame([(1, 2.0)], "t int, gap double")
    for _ in range(2):
        tables.save_log(log, str(tmp_path / "log"))
    assert spark.read.parquet(str(tmp_path / "log")).count() == 2


def test_balancing_ablations_and_experiments(spark, sf):
    rows = {(r["gate"], r["align_mode"], r["overshoot"]): r for r in workloads.balancing_ablations(spark, sf, iterations=60).collect()}
    assert rows[(float("inf"), "walk", "undo_last")]["published"] == 0 < rows[(0.0, "walk", "undo_last")]["published"]
    assert rows[(float("inf"), "walk", "undo_last")]["evicted"] <= rows[(0.0, "walk", "undo_last")]["evicted"]
    out = workloads.release_comparison(spark, sf, workers=8, quorums=(3,), iterations=20, seeds=1)
    assert out.where("method = 'stale_cache'").count() == 4


def test_pca_start_is_hashed():
    p = PCA(10, 6, 2)
    assert np.allclose(p.start(), p.start()) and np.allclose(p.start().T @ p.start(), np.eye(2))
