"""Many runs on a distributed matrix: one kernel call a step, the same results as in one process."""

import numpy as np
import pytest

from stalegrad.operators import gradients as G
from stalegrad.operators.objectives import LeastSquares, Logistic
from stalegrad.plans import loop, workloads
from stalegrad.plans.loop import Options, trace_latency


@pytest.fixture(scope="module")
def rows():
    rng = np.random.default_rng(4)
    return rng.normal(size=(300, 3)), np.where(rng.normal(size=300) > 0, 1.0, -1.0)


class Counting(G.LocalKernel):
    calls = 0

    def answer(self, objective, requests):
        self.calls += 1
        return [(self.value(objective, v) if valued else None, self.parts(objective, spans, v)) for v, spans, valued in requests]


def test_runs_go_side_by_side(rows):
    objective, kernel = Logistic(300, 3), Counting(*rows)
    latency = trace_latency(*np.random.default_rng(5).uniform(1, 9, size=(2, 50, 5)))
    options = [Options(w=2, parts=3, iterations=30), Options(method="gd", w=5, iterations=30, eta=1.0), Options(method="sgd", w=2, parts=3, iterations=30)]
    plans = [loop.plan(300, 5, latency, o) for o in options]
    got = loop.together(kernel, objective, [loop.steps(300, objective, p, o, every=5) for o, p in zip(options, plans)])
    assert kernel.calls <= 31
    for out, o, p in zip(got, options, plans):
        assert out.equals(loop.run(G.LocalKernel(*rows), objective, p, o, every=5))


def test_blocks_give_the_sums_of_the_rows(spark, rows, monkeypatch):
    x, y = rows
    table = spark.createDataFrame([(i + 1, float(y[i]), *map(float, x[i])) for i in range(300)], "sample_idx long, label double, x0 double, x1 double, x2 double")
    monkeypatch.setattr(G, "BLOCK_BYTES", 24 * 40)
    kernel, local = G.BlockKernel(table.repartition(5), 300), G.LocalKernel(x, y)
    v1, v2 = np.random.default_rng(6).normal(size=(2, 3, 1))
    for objective in (Logistic(300, 3), LeastSquares(300, 3, 0.1)):
        requests = [(v1, [(1, 40), (100, 300)], True), (v2, [(7, 7)], False), (v1.copy(), [(2, 3), (301, 400)], False)]
        for (v, spans, valued), (value, parts) in zip(requests, kernel.answer(objective, requests)):
            assert value is None if not valued else np.isclose(value, local.value(objective, v), rtol=1e-12)
            assert np.allclose(parts, local.parts(objective, spans, v), rtol=1e-12, atol=1e-15)
        assert np.isclose(kernel.optimum(objective), objective.optimum(x, y))
    kernel.close()


def test_equal_iterates_are_answered_once(spark, rows):
    """Gradient descent takes the same steps whatever the latencies are; its seeds share them."""
    calls = []

    class Seen(G.BlockKernel):
        def _sums(self, cells):
            calls.append(sum(1 for _ in cells(np.arange(1, 301), rows[1], rows[0])))
            return super()._sums(cells)

    table = spark.createDataFrame([(i + 1, float(rows[1][i]), *map(float, rows[0][i])) for i in range(300)], "sample_idx long, label double, x0 double, x1 double, x2 double")
    v, objective = np.zeros((3, 1)), Logistic(300, 3)
    Seen(table, 300).answer(objective, [(v.copy(), [(1, 100), (101, 300)], True) for _ in range(5)])
    assert calls == [3]


def test_the_value_has_one_logarithm_for_many_rows(rows):
    x, y = np.tile(rows[0], (7, 1)) * 30, np.tile(rows[1], 7)
    objective, v = Logistic(2100, 3), np.array([[3.0], [-2.0], [5.0]])
    assert np.isclose(objective.rows_value(x @ v, y), objective.row_values(x @ v, y).sum(), rtol=1e-13)
    assert objective.rows_value(np.zeros((0, 1)), np.zeros(0)) == 0.0


def test_ablations_make_their_matrix_once(spark, sf, monkeypatch):
    made, problem = [], workloads.problem
    monkeypatch.setattr(workloads, "problem", lambda *a, **k: made.append(1) or problem(*a, **k))
    out = workloads.ablations(spark, sf, workers=4, w=2, iterations=10).collect()
    assert len(made) == 1 and [r.variant for r in out] == ["default", "no_margin", "wide_margin", "no_late_results", "unscaled", "random_order", "endpoint_overlap"]
