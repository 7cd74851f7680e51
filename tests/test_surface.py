"""Streaming equals batch, SQL functions, plans and measures."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from stalegrad.functions.sqlfuncs import register
from stalegrad.operators import latency as L
from stalegrad.operators import matrix as M
from stalegrad.operators import metrics as E
from stalegrad.operators import order_stats as O
from stalegrad.operators import partitioning as P
from stalegrad.plans import workloads
from stalegrad.sources import tables
from stalegrad.streaming import profile as S


@pytest.fixture(scope="module")
def trace(spark, sf):
    tr = L.trace_from_events(tables.load(spark, sf, "events"), 8, 1000.0, 0.4)
    return tr.select("worker", "t", F.col("ts").cast("timestamp").alias("ts"), "comm_ms", "comp_ms", "round_trip_ms").cache()


@pytest.fixture(scope="module")
def trace_files(trace, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("trace") / "t")
    trace.repartitionByRange(3, "ts").sortWithinPartitions("ts").write.parquet(path)
    return path


def rows(df):
    return sorted(map(str, df.collect()))


def test_windowed_profile_stream_equals_batch(spark, trace, trace_files, tmp_path):
    stream = S.windowed_profile(tables.stream_trace(spark, trace_files), "1 day", late="40 days")
    batch = trace.groupBy(F.window("ts", "1 day").alias("span"), "worker").agg(F.count(F.lit(1)).alias("n_obs"), F.round(F.avg("comp_ms"), 6).alias("e"))
    q = stream.writeStream.format("memory").queryName("profile").outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination()
    got = spark.table("profile").select("span", "worker", "n_obs", F.round("e_comp", 6).alias("e"))
    assert rows(got) == rows(batch)


def test_sessions_and_replayed_recordings(spark, trace, trace_files, tmp_path):
    stream = S.deduplicated(tables.stream_trace(spark, trace_files).union(tables.stream_trace(spark, trace_files)), "40 days")
    S.run_once(stream, str(tmp_path / "out"), str(tmp_path / "ck"))
    assert spark.read.parquet(str(tmp_path / "out")).count() == trace.count()
    S.run_once(stream, str(tmp_path / "out"), str(tmp_path / "ck"))  # restarted: nothing twice
    assert spark.read.parquet(str(tmp_path / "out")).count() == trace.count()
    q = S.burst_sessions(tables.stream_trace(spark, trace_files), 1400.0, "12 hours", "40 days").writeStream.format("memory").queryName("bursts").outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("bursts").agg(F.sum("n")).first()[0] == trace.where("comp_ms > 1400").count()


def test_cache_stream_equals_batch_replay(spark, sf, tmp_path):
    from stalegrad.catalog.optimiser_queries import ARRIVALS, cache_replay, layout

    script = spark.createDataFrame(ARRIVALS, "seq long, p int, k int, version int")
    lo, hi = P.sub_bounds_col(F.col("rows"), F.col("p"), F.col("k"))
    path = str(tmp_path / "arrivals")
    arrivals = layout(spark, sf).crossJoin(script).select("seq", "worker", (F.col("first_row") - 1 + lo).alias("lo"), (F.col("first_row") - 1 + hi).alias("hi"), "version")
    for first in (1, 5, 9):
        arrivals.where(F.col("seq").between(first, first + 3)).coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema(arrivals.schema).option("maxFilesPerTrigger", 1).parquet(path)
    S.run_once(S.stream_cache(stream), str(tmp_path / "out"), str(tmp_path / "ck"))
    got = spark.read.parquet(str(tmp_path / "out")).select(F.col("seq").cast("int").alias("seq"), "worker", "action", "n_evicted", "rows_covered")
    assert rows(got) == rows(cache_replay(spark, sf))


def test_exact_moving_profile_stream(spark, trace, trace_files, tmp_path):
    S.run_once(S.exact_moving_profile(tables.stream_trace(spark, trace_files, 10), 5 * 86_400_000), str(tmp_path / "out"), str(tmp_path / "ck"))
    got = {r.worker: (r.n_obs, round(r.e_comp, 6)) for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    last = trace.groupBy("worker").agg(F.max("ts").alias("last"))
    want = trace.join(last, "worker").where(F.col("ts") > F.col("last") - F.expr("INTERVAL 5 DAYS")).groupBy("worker").agg(F.count(F.lit(1)).alias("n"), F.avg("comp_ms").alias("e")).collect()
    assert got == {r.worker: (r.n, round(r.e, 6)) for r in want}


def test_round_trips_of_static_frames(spark):
    t0 = dt.datetime(2024, 1, 1)
    sent = spark.createDataFrame([(1, 7, t0), (2, 7, t0)], "worker int, version int, sent_ts timestamp")
    back = spark.createDataFrame([(1, 7, t0 + dt.timedelta(seconds=2), 1500.0)], "worker int, version int, reply_ts timestamp, comp_ms double")
    r = S.match_round_trips(sent, back).collect()
    assert len(r) == 1 and r[0].round_trip_ms == 2000.0 and r[0].comm_ms == 500.0


def test_sql_surface(spark, sf):
    register(spark, sf)
    assert [tuple(r) for r in spark.sql("SELECT * FROM pieces(10, 3) ORDER BY k").collect()] == [(1, 1, 3), (2, 4, 6), (3, 7, 10)]
    assert spark.sql("SELECT sub_lo(10, 3, 2) AS lo, sub_hi(10, 3, 2) AS hi, align_piece(10, 2, 4, 1) AS j").first() == (4, 6, 3)
    assert spark.sql("SELECT max(step) FROM align_trace(10, 4, 2, 1)").first()[0] == 1
    assert abs(spark.sql("SELECT gamma_cdf(2.0D, 1.0D, 2.0D) AS p").first().p - (1 - 2.718281828459045**-1)) < 1e-12
    assert spark.sql("SELECT count(*) AS n FROM lineitem").first().n == 6000


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_row_ranges_reach_the_scan(spark, sf, tmp_path):
    m = M.logit_matrix(tables.load(spark, sf, "lineitem"), tables.load(spark, sf, "part"))
    n = m.count()
    path = str(tmp_path / "layout")
    tables.write_layout(P.assign(m, n, 8, 10), path)
    laid = spark.read.parquet(path)
    p = plan_of(tables.rows_between(laid.where("worker = 3"), 2000, 2100).select("x0", "label"))
    assert "GreaterThanOrEqual(sample_idx,2000)" in p and "PartitionFilters: [isnotnull(worker" in p and "x5" not in p
    assert laid.groupBy("worker").count().count() == 8


def test_plans_have_no_cartesian_product(spark, sf):
    from stalegrad.catalog import latency_queries as Q

    for name in ("slowness", "overlap_pairs", "burst_share", "moving_profile", "stats_asof"):
        assert "CartesianProduct" not in plan_of(Q.QUERIES[name](spark, sf)), name
    assert "Join" not in plan_of(Q.QUERIES["stats_asof"](spark, sf))


def test_row_ids_do_not_depend_on_partitioning(spark, sf):
    events = tables.load(spark, sf, "events")
    one = {(r.event_id, r.sample_idx) for r in M.index_rows(events, 4, "window").collect()}
    for n in (1, 7):
        assert {(r.event_id, r.sample_idx) for r in M.index_rows(events.repartition(n), 4).collect()} == one
    assert sorted(i for _, i in one) == list(range(1, 1001))


def test_assignment_in_closed_form_and_by_layout(spark):
    ids = spark.range(1, 104).withColumnRenamed("id", "sample_idx")
    closed = P.assign(ids, 103, 4, 5)
    by_join = P.assign_by_layout(P.assign(ids, 103, 4, 5).drop("k"), P.pieces(P.worker_layout(spark, 103, 4), 5))
    assert rows(closed.select("sample_idx", "worker", "k")) == rows(by_join.select("sample_idx", "worker", "k"))


def test_predicted_order_statistics(spark, sf):
    got = workloads.order_stat_models(spark, sf, 8, 4096).agg(*[F.avg(f"error_{m}").alias(m) for m in ("gamma", "iid_gamma", "iid_shifted_exp")]).first()
    assert got.gamma < 0.02 and got.gamma < got.iid_gamma and got.gamma < got.iid_shifted_exp
    stats = L.worker_stats(L.trace_from_events(tables.load(spark, sf, "events"), 8))
    mine = {r.w: r.mean_ms for r in O.predict_order_stats(spark, stats, 8192).collect()}
    s = stats.orderBy("worker").toPandas()
    e, v = s["e_comm"] + s["e_comp"], s["v_comm"] + s["v_comp"]
    assert abs(mine[3] - O.exact_order_stat((e * e / v).to_numpy(), (v / e).to_numpy(), 3)) < 0.01 * mine[3]


def test_measures(spark):
    a = [(1, "a", t, 10.0 * t, 2.0**-t) for t in range(12)]
    b = [(1, "b", t, 20.0 * t, 2.0**-t) for t in range(12)]
    df = spark.createDataFrame(a + b, "run_id int, method string, t int, time_ms double, gap double")
    times = E.time_to_gap(df, [0.1, 1e-9])
    assert {(r.method, r.eps): r.time_ms for r in times.collect()} == {("a", 0.1): 40.0, ("b", 0.1): 80.0, ("a", 1e-9): None, ("b", 1e-9): None}
    assert E.speedup(times, "a", "b").where("eps = 0.1").first().speedup == 2.0
    assert abs(E.rate(df).where("method = 'a'").first().slope + 0.6931471805599453) < 1e-9
    assert E.plateau(df, 3).where("method = 'a'").first().floor == 2.0**-11
    assert {(r.method, r.time_ms): r.gap for r in E.mean_trajectory(df, [45.0]).collect()} == {("a", 45.0): 2.0**-4, ("b", 45.0): 2.0**-2}
    assert len(E.rate_by_phase(df.where("method = 'a'"), [5]).collect()) == 2
    ends = df.where("method = 'a'").select("t", F.col("time_ms").alias("end_ms"))
    slow = ends.withColumn("end_ms", F.col("end_ms") * 3)
    assert E.balance_gain(slow, ends, 5).first().gain == 3.0
    loss = E.lb_precision_loss(df.where("method = 'a'"), df.where("method = 'b'"), [40.0]).first()
    assert loss.loss == 2.0**-2 - 2.0**-4


def test_log_measures(spark, sf):
    log = workloads.delivery_rows(spark, sf).cache()
    n = 6000
    assert E.participation(log, 60).agg(F.sum("u")).first()[0] >= 3.0
    assert E.within_margin(log, 3).where("extra < 0").count() == 0
    health = E.cache_health(log, n)
    assert health.agg(F.max("coverage")).first()[0] <= 1.0 and E.eviction_cost(health, n, 1).first()[0] >= 0
    assert E.staleness_histogram(log).agg(F.sum("n")).first()[0] == log.count()
    assert E.work(log, 7, 1).agg(F.sum("tasks")).first()[0] == log.count()
    assert E.participation_spread(E.participation(log, 60)).first().spread >= 0
    assert E.iteration_latency(log.groupBy(F.col("arrived_in").alias("t")).agg(F.max("finished_ms").alias("end_ms"))).where("latency_ms < 0").count() == 0


def test_trace_files_round_trip(spark, trace, tmp_path):
    path = str(tmp_path / "csv")
    trace.select("worker", "t", "ts", "comm_ms", "comp_ms", "round_trip_ms").write.option("header", True).csv(path)
    assert tables.read_trace(spark, path).count() == trace.count()
    assert abs(L.comm_comp_corr(trace).agg(F.avg("corr")).first()[0]) < 0.3
    assert L.ks_distance(trace, L.worker_stats(trace)).agg(F.max("distance")).first()[0] < 0.3
