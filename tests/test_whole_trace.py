"""The simulator over all recordings, against the recurrence on the whole array."""

from collections import Counter

import numpy as np
import pytest

from stalegrad.catalog import latency_queries
from stalegrad.catalog import optimiser_queries as Q
from stalegrad.operators import simulate


@pytest.fixture(scope="module")
def latency(spark, sf):
    rows = Q.trace(spark, sf).select("t", "worker", "round_trip_ms").collect()
    found = {(r.t, r.worker): r.round_trip_ms for r in rows}
    length = min(max(t for t, i in found if i == w) for w in range(1, Q.N + 1))
    return np.array([[found[t, w] for w in range(1, Q.N + 1)] for t in range(1, length + 1)])


def test_all_iterations(spark, sf, latency):
    want = simulate.recurrence(latency, Q.W, keep_tasks=True)
    assert len(latency) > Q.T
    got = sorted(Q.cumulative_latency(spark, sf).collect())
    assert [r.t for r in got] == list(range(1, len(latency) + 1))
    assert np.allclose([r.cum_ms for r in got], want.ends, atol=1e-3)
    assert np.allclose([r.blind_ms for r in got], np.cumsum(np.sort(latency, axis=1)[:, Q.W - 1]))
    assert [r.n_fresh for r in sorted(Q.sim_iterations(spark, sf).collect())] == want.fresh.sum(axis=1).tolist()
    u = {r.worker: r.u for r in Q.fresh_fraction(spark, sf).collect()}
    assert np.allclose([u[i + 1] for i in range(Q.N)], want.fresh.mean(axis=0), atol=1e-6)
    at = [(version, int(np.searchsorted(want.ends, finish))) for finish, _, version, _ in want.tasks]
    assert {r.staleness: r.n for r in Q.staleness_hist(spark, sf).collect()} == Counter(a - v for v, a in at if a < len(want.ends))


def test_gap_and_contribution(spark, sf, latency):
    for r in Q.carryover_gap(spark, sf).collect():
        assert abs(r.ratio - simulate.recurrence(latency, r.w).ends[-1] / np.sort(latency, axis=1)[:, r.w - 1].sum()) < 1e-5
    rows = {r.worker: r.rows for r in Q.layout(spark, sf).collect()}
    u = simulate.recurrence(latency, Q.W).fresh.mean(axis=0)
    for r in Q.contribution(spark, sf).collect():
        assert abs(r.h - u[r.worker - 1] * rows[r.worker] / (10 * sum(rows.values()))) < 1e-8


def test_coded_rows(spark, sf, latency):
    assert Q.coded_latency(spark, sf).count() == len(latency)


def test_all_pieces_sum_to_the_gradient(spark, sf):
    rows = Q.logistic_subgradients(spark, sf).collect()
    assert len(rows) == 10 * Q.N
    m = Q.logit(spark, sf)
    n = m.count()
    whole = Q.G.ExpressionKernel(m, n).parts(Q.Logistic(n, 7), [(1, n)], np.array(Q.FIXED)[:, None])[0][:, 0]
    assert np.allclose([sum(r[f"g{i}"] for r in rows) for i in range(7)], whole, atol=1e-6)


def test_profile_of_every_event(spark, sf):
    got = latency_queries.stats_asof(spark, sf).collect()
    own = {r.event_id: (r.n_win, r.sum_hundredths) for r in latency_queries.moving_profile(spark, sf).collect()}
    assert {r.event_id: (r.n_win, r.sum_hundredths) for r in got} == own and len(got) == len(own)


def test_never_fastest_of_any_iteration(spark, sf):
    best: dict = {}
    for r in Q.trace(spark, sf).collect():
        best[r.t] = min(best.get(r.t, (float("inf"), 0)), (r.round_trip_ms, r.worker))
    assert {r.worker for r in latency_queries.never_fresh_workers(spark, sf).collect()} == set(range(1, Q.N + 1)) - {w for _, w in best.values()}
