"""Moving profiles of many recordings, and grids that come from the given tables."""

from collections import Counter
from datetime import datetime, timedelta

import numpy as np
import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from stalegrad.catalog import latency_queries as Q
from stalegrad.operators import latency as L
from stalegrad.operators import partitioning as P
from stalegrad.sources.tables import load

TRACE = "worker int, event_id long, ts timestamp_ntz, comm_ms double, comp_ms double"


def frames(trace, micros):
    """The definition: every window summed by itself."""
    w = Window.partitionBy("worker").orderBy("_us").rangeBetween(-micros + 1, 0)
    moments = [f(c).over(w).alias(f"{x}_{c[:4]}") for c in ("comm_ms", "comp_ms") for x, f in (("e", F.avg), ("v", F.var_samp))]
    return trace.withColumn("_us", F.unix_micros(F.col("ts").cast("timestamp"))).select("worker", "event_id", F.count(F.lit(1)).over(w).alias("n_win"), *moments)


def same(got, want):
    a, b = ({r.event_id: r for r in x.collect()} for x in (got, want))
    assert a.keys() == b.keys() and len(a)
    for key, r in a.items():
        assert (r.worker, r.n_win) == (b[key].worker, b[key].n_win)
        for c in ("e_comm", "v_comm", "e_comp", "v_comp"):
            x, y = r[c], b[key][c]
            assert (x is None) == (y is None) and (x is None or np.isclose(x, y, rtol=1e-9, atol=1e-12, equal_nan=True)), (key, c, x, y)


@pytest.mark.parametrize("window, micros", [("1 day", 86_400_000_000), ("1 hour", 3_600_000_000)])
def test_profile_of_given_events(spark, sf, window, micros):
    trace = Q.trace(spark, sf)
    same(L.moving_profile(trace, window), frames(trace, micros))


def test_profile_of_odd_recordings(spark):
    start, nan, inf = datetime(2024, 1, 1), float("nan"), float("inf")
    at = [0, 0, 86_399, 86_400, 86_401, 200_000, 259_200, 345_600, 345_600, 500_000, 700_000]
    comp = [1.0, None, 3.0, 1e9, 4.0, nan, 5.0, inf, -inf, inf, 2.0]
    rows = [(w, 100 * w + i, start + timedelta(seconds=s), None if i % 3 == 0 else 0.1 * i, comp[(i + w) % len(comp)]) for w in (1, 2, 3) for i, s in enumerate(at)]
    trace = spark.createDataFrame([*rows, (1, 1, None, 1.0, 2.0), (1, 2, None, 3.0, 5.0), (None, 3, start, 1.0, 1.0)], TRACE)
    same(L.moving_profile(trace), frames(trace, 86_400_000_000))


def test_profile_has_no_frame_that_is_summed_again_for_every_row(spark, sf):
    plan = L.moving_profile(Q.trace(spark, sf))._jdf.queryExecution().executedPlan().toString()
    assert "RangeFrame, -" not in plan and "FlatMapGroupsInArrow" in plan


def test_grids_follow_the_lines_of_each_worker(spark, sf):
    held = Counter(r.l_suppkey % Q.N + 1 for r in load(spark, sf, "lineitem").select("l_suppkey").collect())
    cells = {(w, p, p2, k) for w in held for p in range(1, 13) for p2 in range(1, 13) for k in range(1, p + 1)}
    moved = {(r.worker, r.p, r.p2, r.k): r.j for r in Q.translate_index(spark, sf).collect()}
    assert moved == {(w, p, p2, k): P.translate(held[w], p, p2, k) for w, p, p2, k in cells}
    walked = {(r.worker, r.p, r.p2, r.k): r.j for r in Q.align_index(spark, sf).collect()}
    assert walked == {(w, p, p2, k): P.align(held[w], p, p2, k) for w, p, p2, k in cells}


def test_burst_chance_follows_the_recordings(spark, sf):
    share = sum(r.n for r in Q.burst_islands(spark, sf).collect()) / load(spark, sf, "events").count()
    got = {r.n_workers: r.p for r in Q.no_burst_probability(spark, sf).collect()}
    assert share > 0 and got == {n: pytest.approx((1 - share) ** n, abs=1e-6) for n in (8, 36, 72, 100, 1000)}
