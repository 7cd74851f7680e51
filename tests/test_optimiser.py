"""Methods against brute force, degenerate cases and the reported behaviour."""

import numpy as np
import pandas as pd
import pytest

from stalegrad.functions.draws import gamma_cdf, gamma_draws
from stalegrad.operators import gradients as G
from stalegrad.operators import matrix as M
from stalegrad.operators.objectives import PCA, LeastSquares, Logistic, explained_variance, power_iteration
from stalegrad.operators.order_stats import exact_order_stat
from stalegrad.operators.simulate import heap, recurrence
from stalegrad.plans.balancer import Balancer, Simulator, baseline_bound, brute_force, contribution, equalize, imbalance, rebalance, should_distribute
from stalegrad.plans.loop import Options, coded_bound, coded_sweep, delivery_log, gamma_latency, optimise, plan, trace_latency
from stalegrad.plans.workloads import balancing_script, block_latencies, sub_bounds
from stalegrad.sources.tables import load

RNG = np.random.default_rng(0)


@pytest.mark.parametrize("margin", [0.0, 0.02, 0.3])
def test_queue_equals_recurrence(margin):
    for seed in range(60):
        rng = np.random.default_rng(seed)
        n = int(rng.integers(2, 14))
        x, w = rng.gamma(2, 1, (40, n)), int(rng.integers(1, n + 1))
        a, b = recurrence(x, w, margin), heap(x, w, margin)
        assert np.array_equal(a.ends, b.ends) and np.array_equal(a.fresh, b.fresh)


def test_equal_latencies_leave_everyone_fresh():
    assert recurrence(np.ones((10, 5)), 2).fresh.all()


def ramp_stats(n: int, amount: float = 0.4) -> pd.DataFrame:
    f = 1 + amount * np.arange(1, n + 1) / n
    return pd.DataFrame({"worker": np.arange(1, n + 1), "e_comm": 5.0, "v_comm": 8.0, "e_comp": 1050 * f, "v_comp": 2500 * f * f})


def logit_problem(n=3000, d=6):
    x = RNG.normal(size=(n, d))
    y = np.where(RNG.random(n) < 1 / (1 + np.exp(-x @ RNG.normal(size=d))), 1.0, -1.0)
    kernel = G.LocalKernel(x, y)
    o = Logistic(n, d)
    return kernel, o, o.optimum(x, y)


def test_gd_is_power_iteration_for_pca():
    x = (RNG.random((200, 20)) < 0.3).astype(float)
    p = PCA(200, 20, 3, float((x * x).sum()))
    out = optimise(G.LocalKernel(x), p, 4, gamma_latency(ramp_stats(4)), Options(method="gd", w=4, iterations=12, eta=1.0), p.optimum(x, None))
    v = power_iteration(x, p.start(), 12)
    assert abs(-out["objective"].iloc[-1] - explained_variance(x, v)) < 1e-12


def test_one_piece_and_all_workers_is_gd():
    kernel, o, best = logit_problem()
    lat = gamma_latency(ramp_stats(5))
    a = optimise(kernel, o, 5, lat, Options(method="stale_cache", w=5, parts=1, iterations=15, eta=1.0, margin=0), best)
    b = optimise(kernel, o, 5, lat, Options(method="gd", w=5, iterations=15, eta=1.0), best)
    assert np.allclose(a["objective"], b["objective"], atol=1e-12)


def test_waiting_for_all_is_the_averaged_gradient():
    kernel, o, best = logit_problem()
    lat = gamma_latency(ramp_stats(5))
    a, b = (optimise(kernel, o, 5, lat, Options(method=m, w=5, parts=4, iterations=25, margin=0), best) for m in ("stale_cache", "avg_gradient"))
    assert np.allclose(a["objective"], b["objective"], atol=1e-13)


def test_closed_gate_is_the_averaged_gradient():
    kernel, o, best = logit_problem()
    lat = gamma_latency(ramp_stats(6))
    a = optimise(kernel, o, 6, lat, Options(w=2, parts=4, iterations=40, use_late=False), best)
    b = optimise(kernel, o, 6, lat, Options(method="avg_gradient", w=2, parts=4, iterations=40), best)
    assert a["gap"].tolist() == b["gap"].tolist()


def online(kernel, o, n_workers, comm, comp, w, parts, iterations, eta):
    """The method as an explicit online loop over an event list and a row-wise cache."""
    n, k = kernel.n, 0
    blocks = [sub_bounds(n, n_workers, i + 1) for i in range(n_workers)]
    v, now = o.start(), 0.0
    free, done, running = [0.0] * n_workers, [0] * n_workers, []
    cache, trace = {}, []
    for t in range(iterations):
        tasks = []
        for i, (lo, hi) in enumerate(blocks):
            m, piece = hi - lo + 1, done[i] % parts + 1
            a, b = sub_bounds(m, parts, piece)
            begin = max(now, free[i])
            tasks.append((begin, begin + comm[done[i] % len(comm), i] + comp[done[i] % len(comp), i] * (b - a + 1) * parts / m, i, t, lo - 1 + a, lo - 1 + b))
        end = sorted(x[1] for x in tasks)[w - 1]
        for x in tasks:
            if x[0] < end or x[1] <= end:
                running.append((*x, o.part(kernel.x[x[4] - 1 : x[5]], kernel.y[x[4] - 1 : x[5]], v)))
                free[x[2]] = x[1]
                done[x[2]] += 1
        for x in sorted((x for x in running if x[1] <= end), key=lambda x: (x[1], x[2])):
            key = (x[4], x[5])
            if key not in cache or cache[key][0] < x[3]:
                cache[key] = (x[3], x[6])
        running = [x for x in running if x[1] > end]
        share = sum(b - a + 1 for a, b in cache) / n
        v = v - eta * (sum(g for _, g in cache.values()) / share + o.regulariser_grad(v))
        now = end
        trace.append((now, kernel.value(o, v)))
        k += 1
    return trace


def test_virtual_plan_equals_the_online_loop():
    kernel, o, best = logit_problem(600, 4)
    comm, comp = RNG.gamma(2, 1, (37, 6)), RNG.gamma(3, 20, (37, 6))
    want = online(kernel, o, 6, comm, comp, 2, 3, 50, 0.25)
    got = optimise(kernel, o, 6, trace_latency(comm, comp), Options(w=2, parts=3, iterations=50, margin=0), best)
    assert np.allclose(got["time_ms"].iloc[1:], [x[0] for x in want]) and np.allclose(got["objective"].iloc[1:], [x[1] for x in want], atol=1e-12)


@pytest.fixture(scope="module")
def logit01(spark):
    d = "/root/testdata/sf0.01"
    kernel = G.local_logistic(M.logit_matrix(load(spark, d, "lineitem"), load(spark, d, "part")))
    o = Logistic(kernel.n, 7)
    return kernel, o, o.optimum(kernel.x, kernel.y)


def test_reported_order_of_the_methods(logit01):
    kernel, o, best = logit01
    n, lat = 49, gamma_latency(ramp_stats(49), 1)

    def time(method, w, iterations, eta=0.25, **kw):
        out = optimise(kernel, o, n, lat, Options(method=method, w=w, iterations=iterations, eta=eta, **kw), best, every=5)
        hit = out[out["gap"] <= 1e-8]
        return (hit["time_ms"].iloc[0] if len(hit) else np.inf), out

    sc, _ = time("stale_cache", 10, 600)
    ag, _ = time("avg_gradient", n, 600)
    gd, gd_run = time("gd", n, 150, 1.0)
    assert sc < 0.85 * ag and 2 * sc < gd and 2 * ag < gd
    for method in ("sgd", "avg_gradient"):  # both stop far above it
        never, out = time(method, 10, 600)
        assert never == np.inf and out["gap"].min() > 1e-6
    comm, comp = block_latencies(ramp_stats(n), 150)
    sweep = coded_sweep(optimise(kernel, o, n, lat, Options(method="gd", w=n, iterations=150, eta=1.0), best), comm, comp, [(45, 49), (1, 2)], 1e-8).set_index("rate")["time_ms"]
    assert sweep.loc[45 / 49] > 2 * sc and sweep.loc[0.5] > sweep.loc[45 / 49]


def test_balancing_helps_when_workers_differ(logit01):
    kernel, o, best = logit01
    rows = np.array([b - a + 1 for a, b in (sub_bounds(kernel.n, 8, i + 1) for i in range(8))])
    opts = Options(w=8, iterations=140, parts=100)
    lat = gamma_latency(ramp_stats(8, 0.0), 3, balancing_script())
    balancer = Balancer(rows, np.full(8, 100), 8, solve_delay=2000.0)
    plain, balanced = plan(kernel.n, 8, lat, opts), plan(kernel.n, 8, lat, opts, balancer)
    gain = (plain.ends[-1] - plain.ends[-21]) / (balanced.ends[-1] - balanced.ends[-21])
    assert gain > 1.5 and any(e["distributed"] for e in balancer.events)


def test_rebalance_bounds_and_equal_expectations():
    stats, rows, parts = ramp_stats(8), np.full(8, 7500), np.full(8, 100)
    sim = Simulator(4)
    h = baseline_bound(stats, rows, parts, parts, sim)
    new = rebalance(stats, rows, parts, h, sim, overshoot="undo_last")
    ec, ep = stats["e_comm"].to_numpy(), stats["e_comp"].to_numpy()
    assert imbalance(ec, ep * parts / new) < imbalance(ec, ep)
    assert contribution(sim.fresh(ec, stats["v_comm"], ep * parts / new, stats["v_comp"] * (parts / new) ** 2), rows, new) >= 0.97 * h
    first = equalize(ec, ep, parts)
    assert first[-1] == 100 and (first <= 100).all()
    assert should_distribute(1.3, 1.1) and not should_distribute(1.1, 1.05)


def test_greedy_balancer_is_near_brute_force():
    stats, rows, parts = ramp_stats(3), np.full(3, 1000), np.full(3, 20)
    sim = Simulator(3, replicates=2)
    h = baseline_bound(stats, rows, parts, parts, sim)
    ec, ep = stats["e_comm"].to_numpy(), stats["e_comp"].to_numpy()
    best = brute_force(stats, rows, parts, h, sim, list(range(14, 28)))
    mine = rebalance(stats, rows, parts, h, sim, overshoot="undo_last")
    assert imbalance(ec, ep * parts / mine) <= 1.12 * imbalance(ec, ep * parts / best)


def test_walk_alignment_keeps_more_rows():
    from stalegrad.operators import partitioning  # noqa: F401

    class Switch:
        def counts(self, t, now, wanted):
            return [10 if (t // 25) % 2 == 0 else 15] * len(wanted)

        def record(self, task, now):
            pass

    missing = {}
    for mode in ("walk", "none"):
        p = plan(12_000, 4, gamma_latency(ramp_stats(4)), Options(w=4, iterations=200, align_mode=mode), Switch())
        missing[mode] = sum(12_000 - c for c in p.covered[40:])
    assert missing["walk"] <= missing["none"]


def test_delivery_log_is_consistent():
    p = plan(4000, 6, gamma_latency(ramp_stats(6)), Options(w=2, parts=5, iterations=60))
    log = delivery_log(p)
    assert (log["arrived_in"] >= log["version"]).all() and (log["fresh"] == (log["arrived_in"] == log["version"])).all()
    gained = (log["hi"] - log["lo"] + 1 - log["rows_evicted"]).where(log["action"].isin(["insert", "replace"]), 0)
    assert gained.sum() == p.covered[-1]


def test_carry_over_is_underestimated_for_small_quorums():
    x = gamma_draws(np.random.default_rng(1), ramp_stats(20)["e_comp"], ramp_stats(20)["v_comp"], (200, 20))
    blind = {w: np.sort(x, axis=1)[:, w - 1].sum() for w in (3, 20)}
    assert recurrence(x, 3).ends[-1] > 1.01 * blind[3] and abs(recurrence(x, 20).ends[-1] - blind[20]) < 1e-6 * blind[20]


def test_exact_order_statistics_of_exponentials():
    n, mean = 6, 3.0
    for w in (1, 3, 6):
        want = mean * sum(1 / (n - i) for i in range(w))
        assert abs(exact_order_stat(np.ones(n), np.full(n, mean), w, 40_000) - want) < 0.02 * want


def test_gamma_cdf_and_moments():
    assert np.allclose(gamma_cdf([0.0, 1.0, 5.0], 1.0, 2.0), 1 - np.exp(-np.array([0, 0.5, 2.5])), atol=1e-12)
    x = gamma_draws(np.random.default_rng(0), np.array([10.0, 4.0]), np.array([5.0, 0.0]), (20_000, 2))
    assert abs(x[:, 0].mean() - 10) < 0.1 and abs(x[:, 0].var() - 5) < 0.3 and (x[:, 1] == 4).all()


def test_least_squares_and_decaying_steps():
    x = RNG.normal(size=(500, 4))
    y = x @ np.array([1.0, -2.0, 0.5, 3.0]) + 0.1 * RNG.normal(size=500)
    o = LeastSquares(500, 4, 0.01)
    out = optimise(G.LocalKernel(x, y), o, 4, gamma_latency(ramp_stats(4)), Options(w=2, parts=5, iterations=200, eta=0.3), o.optimum(x, y))
    assert out["gap"].iloc[-1] < 1e-8
    slow = optimise(G.LocalKernel(x, y), o, 4, gamma_latency(ramp_stats(4)), Options(method="sgd", w=2, parts=5, iterations=200, eta_schedule=lambda t: 0.5 / (1 + t / 20)), o.optimum(x, y))
    assert slow["gap"].iloc[-1] < 0.1


def test_spark_kernels_agree_with_numpy(spark, sf):
    m = M.logit_matrix(load(spark, sf, "lineitem"), load(spark, sf, "part"))
    local, v, tasks = G.local_logistic(m), RNG.normal(size=(7, 1)), [(1, 90), (700, 1500), (5000, 5003)]
    o = Logistic(local.n, 7)
    far = G.ExpressionKernel(m, local.n)
    assert np.allclose(local.parts(o, tasks, v), far.parts(o, tasks, v), atol=1e-12) and abs(local.value(o, v) - far.value(o, v)) < 1e-12
    t = M.token_matrix(spark.read.parquet(f"{sf}/documents.parquet"), 128)
    dense = G.local_sparse(t, 128)
    p = PCA(dense.n, 128, 3, float((dense.x**2).sum()))
    far, v = G.ArrowKernel(t, 128), p.start()
    assert np.allclose(dense.parts(p, [(1, 20), (30, 90)], v), far.parts(p, [(1, 20), (30, 90)], v), atol=1e-9) and abs(dense.value(p, v) - far.value(p, v)) < 1e-12
    assert G.choose_kernel(7, 1.0, 10**9) == "expression" and G.choose_kernel(2504, 0.05, 10**8) == "arrow" and G.choose_kernel(7, 1.0, 100) == "local"
