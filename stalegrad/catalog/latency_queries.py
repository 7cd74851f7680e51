"""Relational queries on latency, order statistics and layouts, each with its SQL oracle."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stalegrad.operators import latency as L
from stalegrad.operators import metrics
from stalegrad.operators import order_stats as O
from stalegrad.operators import partitioning as P
from stalegrad.sources.tables import load, written

N = 8
QUERIES, ORACLES = {}, {}

TRACE = f"""trace AS (
  SELECT CAST(user_id % {N} + 1 AS INTEGER) AS worker,
         CAST(row_number() OVER (PARTITION BY user_id % {N} ORDER BY ts, event_id) AS INTEGER) AS t,
         event_id, ts, CAST(json_extract_string(props, '$.k') AS DOUBLE) / 10 + 0.1 AS comm_ms, 1000.0 + value AS comp_ms,
         CAST(json_extract_string(props, '$.k') AS DOUBLE) / 10 + 0.1 + (1000.0 + value) AS round_trip_ms
  FROM events)"""
STATS = """stats AS (
  SELECT worker, count(*) AS n_obs, avg(comm_ms) AS e_comm, var_samp(comm_ms) AS v_comm, avg(comp_ms) AS e_comp, var_samp(comp_ms) AS v_comp
  FROM trace GROUP BY worker)"""


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def trace(spark: SparkSession, sf_dir: str, n: int = N, ramp: float = 0.0) -> DataFrame:
    return L.trace_from_events(load(spark, sf_dir, "events"), n, 1000.0, ramp)


def r6(*names: str):
    return [F.round(F.col(c), 6).alias(c) for c in names]


@query(f"WITH {TRACE} SELECT worker, t, event_id, round(comm_ms, 6) AS comm_ms, round(comp_ms, 6) AS comp_ms, round(round_trip_ms, 6) AS round_trip_ms FROM trace")
def trace_events(spark, d):
    return trace(spark, d).select("worker", "t", "event_id", *r6("comm_ms", "comp_ms", "round_trip_ms"))


@query(f"WITH {TRACE}, {STATS} SELECT worker, n_obs, round(e_comm, 6) AS e_comm, round(v_comm, 6) AS v_comm, round(e_comp, 6) AS e_comp, round(v_comp, 6) AS v_comp FROM stats")
def worker_stats(spark, d):
    return L.worker_stats(trace(spark, d)).select("worker", "n_obs", *r6("e_comm", "v_comm", "e_comp", "v_comp"))


@query(f"WITH {TRACE}, {STATS} SELECT worker, round(e_comp * e_comp / v_comp, 6) AS shape, round(v_comp / e_comp, 6) AS scale FROM stats")
def gamma_params(spark, d):
    return L.gamma_moments(L.worker_stats(trace(spark, d))).select("worker", *r6("shape", "scale"))


@query(f"WITH {TRACE}, {STATS} SELECT worker, round(e_comm + e_comp, 6) AS e_total, round(v_comm + v_comp, 6) AS v_total FROM stats")
def total_moments(spark, d):
    return L.total_moments(L.worker_stats(trace(spark, d))).select("worker", *r6("e_total", "v_total"))


@query(f"WITH {TRACE} SELECT round(avg(comm_ms), 6) AS e_comm, round(var_samp(comm_ms), 6) AS v_comm, round(avg(comp_ms), 6) AS e_comp, round(var_samp(comp_ms), 6) AS v_comp FROM trace")
def iid_stats(spark, d):
    return L.iid_stats(trace(spark, d)).select(*r6("e_comm", "v_comm", "e_comp", "v_comp"))


@query(f"WITH {TRACE}, {STATS} SELECT worker, round(1 / sqrt(v_comp), 6) AS rate, round(e_comp - sqrt(v_comp), 6) AS shift FROM stats")
def shifted_exp_params(spark, d):
    return L.shifted_exp_moments(L.worker_stats(trace(spark, d))).select("worker", *r6("rate", "shift"))


@query(f"""WITH {TRACE}, m AS (SELECT worker, comp_ms, comp_ms > avg(comp_ms) OVER (PARTITION BY worker) AS high FROM trace)
SELECT worker, round(avg(comp_ms) FILTER (WHERE NOT high), 6) AS low_ms, round(avg(comp_ms) FILTER (WHERE high), 6) AS high_ms, round(avg(CASE WHEN high THEN 1.0 ELSE 0.0 END), 6) AS p_high FROM m GROUP BY worker""")
def two_level(spark, d):
    return L.two_level_fit(trace(spark, d)).select("worker", *r6("low_ms", "high_ms", "p_high"))


@query(f"WITH {TRACE} SELECT worker, round(round_trip_ms, 6) AS latency, round(cume_dist() OVER (PARTITION BY worker ORDER BY round_trip_ms), 6) AS cdf FROM trace")
def latency_cdf(spark, d):
    return L.empirical_cdf(trace(spark, d)).select("worker", *r6("latency", "cdf"))


@query()
def gamma_fit_distance(spark, d):
    """Largest distance between empirical and fitted CDF (the gamma CDF is beyond SQL)."""
    tr = trace(spark, d)
    return L.ks_distance(tr, L.worker_stats(tr)).select("worker", *r6("distance"))


@query(f"WITH {TRACE} SELECT worker, round(corr(comm_ms, comp_ms), 6) AS corr FROM trace GROUP BY worker")
def comm_comp_corr(spark, d):
    return L.comm_comp_corr(trace(spark, d)).select("worker", *r6("corr"))


@query(f"WITH {TRACE}, {STATS} SELECT worker, round((e_comm + e_comp) / min(e_comm + e_comp) OVER (), 6) AS slowness FROM stats")
def slowness(spark, d):
    return L.slowness(L.worker_stats(trace(spark, d))).select("worker", *r6("slowness"))


_POINTS = f"""{TRACE}, sized AS (SELECT trace.*, load FROM trace, (VALUES (1), (2), (4), (8)) AS l(load)),
blocks AS (SELECT worker, load, (t - 1) // load AS block, sum(comp_ms) AS comp, count(*) AS n FROM sized GROUP BY 1, 2, 3),
points AS (SELECT worker, load, avg(comp) AS mean, var_samp(comp) AS variance FROM blocks WHERE n = load GROUP BY 1, 2)"""


@query(f"WITH {_POINTS} SELECT worker, load, round(mean, 6) AS mean, round(variance, 4) AS variance FROM points")
def load_points(spark, d):
    return L.load_points(trace(spark, d), [1, 2, 4, 8]).select("worker", "load", F.round("mean", 6).alias("mean"), F.round("variance", 4).alias("variance"))


@query(f"""WITH {_POINTS}, long AS (SELECT 'mean' AS what, load, mean AS y FROM points UNION ALL SELECT 'variance', load, variance FROM points)
SELECT what, round(sum(load * y) / sum(load * load), 4) AS slope, round(sum(load * y) * sum(load * y) / (sum(load * load) * sum(y * y)), 6) AS r2 FROM long WHERE y IS NOT NULL GROUP BY what""")
def load_origin_fit(spark, d):
    return L.origin_fit(L.load_points(trace(spark, d), [1, 2, 4, 8])).select("what", F.round("slope", 4).alias("slope"), *r6("r2"))


@query(f"""WITH {TRACE}, us AS (SELECT *, epoch_us(ts) AS u FROM trace)
SELECT worker, event_id, count(*) OVER w AS n_win, CAST(round(avg(comp_ms) OVER w * count(*) OVER w * 100) AS BIGINT) AS sum_hundredths FROM us
WINDOW w AS (PARTITION BY worker ORDER BY u RANGE BETWEEN 86399999999 PRECEDING AND CURRENT ROW)""")
def moving_profile(spark, d):
    total = F.round(F.col("e_comp") * F.col("n_win") * 100).cast("long")  # whole, so no rounding ties
    return L.moving_profile(trace(spark, d), "1 day").select("worker", "event_id", "n_win", total.alias("sum_hundredths"))


#: Scripted bursts: (worker, from_t, to_t, factor)
BURSTS = [(1, 20, 45, 1.3), (3, 30, 60, 1.3), (6, 50, 70, 1.25)]
_BURST = f"""{TRACE}, script(worker, from_t, to_t, factor) AS (VALUES {', '.join(map(str, BURSTS))}),
slow AS (SELECT trace.worker, trace.t, comp_ms * CASE WHEN t >= from_t AND t < to_t THEN factor ELSE 1.0 END AS comp_ms FROM trace LEFT JOIN script USING (worker)),
base AS (SELECT worker, quantile_cont(comp_ms, 0.5) AS b FROM slow GROUP BY worker),
roll AS (SELECT worker, t, avg(comp_ms) OVER (PARTITION BY worker ORDER BY t ROWS BETWEEN 4 PRECEDING AND 4 FOLLOWING) AS r FROM slow),
hot AS (SELECT worker, t, t - row_number() OVER (PARTITION BY worker ORDER BY t) AS island FROM roll JOIN base USING (worker) WHERE r > 1.12 * b),
islands AS (SELECT worker, min(t) AS start_t, max(t) AS end_t, count(*) AS n FROM hot GROUP BY worker, island)"""


def scripted(spark, d):
    script = spark.createDataFrame(BURSTS, "worker int, from_t int, to_t int, factor double")
    return L.perturb(trace(spark, d), script)


@query(f"WITH {_BURST} SELECT worker, start_t, end_t, n FROM islands")
def burst_islands(spark, d):
    return L.bursts(scripted(spark, d))


@query(f"""WITH {_BURST}, ts AS (SELECT DISTINCT t FROM trace), hit AS (SELECT count(*) AS h FROM ts WHERE EXISTS (SELECT 1 FROM hot WHERE hot.t = ts.t))
SELECT round((SELECT h FROM hit) / (SELECT count(*) FROM ts), 6) AS share, (SELECT count(DISTINCT worker) FROM islands) AS workers""")
def burst_share(spark, d):
    tr = scripted(spark, d)
    return L.burst_share(tr, L.bursts(tr)).select(*r6("share"), "workers")


@query(f"""WITH {_BURST}, share AS (SELECT coalesce((SELECT sum(n) FROM islands), 0) / (SELECT count(*) FROM trace) AS p)
SELECT CAST(v.n AS INTEGER) AS n_workers, round(pow(1 - p, v.n), 6) AS p FROM share, (VALUES (8), (36), (72), (100), (1000)) AS v(n)""")
def no_burst_probability(spark, d):
    """Chance that none of n workers is in a burst, from the share of recordings inside bursts."""
    tr = scripted(spark, d)
    inside, recorded = L.bursts(tr).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("inside")), tr.agg(F.count(F.lit(1)).alias("recorded"))
    share = inside.crossJoin(F.broadcast(recorded)).select((F.col("inside") / F.col("recorded")).alias("share"))
    n = spark.createDataFrame([(x,) for x in (8, 36, 72, 100, 1000)], "n_workers int")
    return n.crossJoin(F.broadcast(share)).select("n_workers", F.round(L.no_burst_probability(F.col("share"), F.col("n_workers")), 6).alias("p"))


@query(f"WITH {TRACE}, {STATS} SELECT worker, round(e_comp * (1 + 0.4 * worker / {N}), 6) AS e_comp, round(v_comp * (1 + 0.4 * worker / {N}) * (1 + 0.4 * worker / {N}), 6) AS v_comp FROM stats")
def slow_ramp(spark, d):
    return L.slow_ramp(L.worker_stats(trace(spark, d)), N).select("worker", *r6("e_comp", "v_comp"))


@query(f"""WITH {TRACE}, full_t AS (SELECT t FROM trace GROUP BY t HAVING count(*) = {N}),
r AS (SELECT row_number() OVER (PARTITION BY t ORDER BY round_trip_ms, worker) AS w, round_trip_ms FROM trace WHERE t IN (SELECT t FROM full_t))
SELECT CAST(w AS INTEGER) AS w, round(avg(round_trip_ms), 6) AS mean_ms FROM r GROUP BY w""")
def order_stats_empirical(spark, d):
    return O.empirical_order_stats(trace(spark, d), N).select("w", *r6("mean_ms"))


def _mc_sql(rates: str, seed: int, draws: int) -> str:
    return f"""WITH {TRACE}, {STATS}, rates AS ({rates}),
u AS (SELECT r, worker, (CAST('0x' || substr(md5('{seed}|' || r || '|' || worker), 1, 12) AS BIGINT) + 0.5) / 281474976710656.0 AS u, rate, shift FROM rates, range(1, {draws + 1}) AS g(r)),
o AS (SELECT row_number() OVER (PARTITION BY r ORDER BY shift - ln(u) / rate, worker) AS w, shift - ln(u) / rate AS ms FROM u)
SELECT CAST(w AS INTEGER) AS w, round(avg(ms), 6) AS mean_ms FROM o GROUP BY w"""


@query(_mc_sql("SELECT worker, 1 / sqrt(v_comp) AS rate, e_comp - sqrt(v_comp) AS shift FROM stats", 5, 200))
def order_stats_mc(spark, d):
    return O.hashed_order_stats(L.shifted_exp_moments(L.worker_stats(trace(spark, d))), 200, 5).select("w", *r6("mean_ms"))


@query(_mc_sql(f"SELECT worker, 1 / (SELECT sqrt(var_samp(comp_ms)) FROM trace) AS rate, (SELECT avg(comp_ms) - sqrt(var_samp(comp_ms)) FROM trace) AS shift FROM range(1, {N + 1}) AS x(worker)", 6, 200))
def order_stats_iid_mc(spark, d):
    one = L.iid_stats(trace(spark, d)).select((1 / F.sqrt("v_comp")).alias("rate"), (F.col("e_comp") - F.sqrt("v_comp")).alias("shift"))
    rates = spark.range(1, N + 1).select(F.col("id").cast("int").alias("worker")).crossJoin(F.broadcast(one))
    return O.hashed_order_stats(rates, 200, 6).select("w", *r6("mean_ms"))


@query(f"WITH {TRACE}, m AS (SELECT worker, avg(comm_ms) AS a, avg(comp_ms) AS b FROM trace GROUP BY worker) SELECT 'comm' AS part, round(min(a), 6) AS min_ms, round(max(a), 6) AS max_ms FROM m UNION ALL SELECT 'comp', round(min(b), 6), round(max(b), 6) FROM m")
def latency_ranges(spark, d):
    return L.latency_ranges(trace(spark, d)).select("part", *r6("min_ms", "max_ms"))


@query(f"WITH {TRACE}, {STATS} SELECT CAST(rank AS INTEGER) AS rank, worker FROM (SELECT worker, row_number() OVER (ORDER BY e_comm + e_comp, worker) AS rank FROM stats) WHERE rank <= 3")
def best_workers_topk(spark, d):
    best = L.total_moments(L.worker_stats(trace(spark, d))).orderBy("e_total", "worker").limit(3)
    return best.select(F.row_number().over(Window.orderBy("e_total", "worker")).alias("rank"), "worker")


@query(f"""WITH {TRACE}, us AS (SELECT *, epoch_us(ts) AS u FROM trace),
pre AS (SELECT worker, ts, count(*) OVER w AS n_win, CAST(round(avg(comp_ms) OVER w * count(*) OVER w * 100) AS BIGINT) AS sum_hundredths FROM us
WINDOW w AS (PARTITION BY worker ORDER BY u RANGE BETWEEN 86399999999 PRECEDING AND CURRENT ROW))
SELECT a.worker, a.event_id, p.n_win, p.sum_hundredths FROM trace a ASOF LEFT JOIN pre p ON a.worker = p.worker AND a.ts >= p.ts""")
def stats_asof(spark, d):
    """Every event with the moving profile in force at its time."""
    tr = trace(spark, d)
    total = F.round(F.col("e_comp") * F.col("n_win") * 100).cast("long")
    profile = L.moving_profile(tr, "1 day").select("worker", "ts", "n_win", total.alias("sum_hundredths"))
    return metrics.asof_last(tr.select("worker", "ts", "event_id"), profile, "worker", "ts", ["n_win", "sum_hundredths"]).select("worker", "event_id", "n_win", "sum_hundredths")


_N = "(SELECT count(*) FROM lineitem)"
BLOCKS = f"blocks AS (SELECT CAST(w AS INTEGER) AS worker, (w - 1) * {_N} // {N} + 1 AS first_row, w * {_N} // {N} AS last_row FROM range(1, {N + 1}) AS r(w))"


def layout(spark, d):
    return P.worker_layout(spark, load(spark, d, "lineitem").count(), N)


@query(f"WITH {BLOCKS} SELECT worker, first_row, last_row, last_row - first_row + 1 AS rows FROM blocks")
def worker_blocks(spark, d):
    return layout(spark, d)


_PIECES = BLOCKS + """, pieces AS (SELECT worker, CAST(p AS INTEGER) AS parts, CAST(k AS INTEGER) AS k, first_row - 1 + (k - 1) * (last_row - first_row + 1) // p + 1 AS lo, first_row - 1 + k * (last_row - first_row + 1) // p AS hi
FROM blocks, (VALUES (2), (3), (10)) AS v(p), range(1, 11) AS r(k) WHERE k <= p)"""


def three_layouts(spark, d):
    base = layout(spark, d)
    return P.pieces(base, 2).unionByName(P.pieces(base, 3)).unionByName(P.pieces(base, 10))


@query(f"WITH {_PIECES} SELECT worker, parts, k, lo, hi FROM pieces")
def sub_bounds(spark, d):
    return three_layouts(spark, d)


@query(f"WITH {_PIECES} SELECT worker, parts, min(hi - lo + 1) AS least, max(hi - lo + 1) AS most, CAST(sum(hi - lo + 1) AS BIGINT) AS rows FROM pieces GROUP BY worker, parts")
def sub_sizes(spark, d):
    size = F.col("hi") - F.col("lo") + 1
    return three_layouts(spark, d).groupBy("worker", "parts").agg(F.min(size).alias("least"), F.max(size).alias("most"), F.sum(size).alias("rows"))


@query(f"""WITH {_PIECES} SELECT a.worker, a.k AS old_k, b.k AS new_k, least(a.hi, b.hi) - greatest(a.lo, b.lo) + 1 AS shared
FROM pieces a JOIN pieces b ON a.worker = b.worker AND a.parts = 2 AND b.parts = 3 AND a.lo <= b.hi AND a.hi >= b.lo""")
def overlap_pairs(spark, d):
    base = layout(spark, d)
    both = P.overlaps(P.pieces(base, 2), P.pieces(base, 3))
    shared = F.least("hi", "new_hi") - F.greatest("lo", "new_lo") + 1
    return both.select("worker", F.col("k").alias("old_k"), F.col("new_k"), shared.alias("shared"))


_GRID = f"""grid AS (SELECT worker, rows, p, p2, k FROM (SELECT CAST(l_suppkey % {N} + 1 AS INTEGER) AS worker, count(*) AS rows FROM lineitem GROUP BY 1),
range(1, 13) AS a(p), range(1, 13) AS b(p2), range(1, 13) AS c(k) WHERE k <= p)"""


def grid(spark, d):
    """Changes of the piece count for every worker, each holding the lines of its suppliers."""
    held = load(spark, d, "lineitem").groupBy((F.pmod("l_suppkey", F.lit(N)) + 1).cast("int").alias("worker")).agg(F.count(F.lit(1)).alias("rows"))
    p, p2, k = (spark.range(1, 13).withColumnRenamed("id", c) for c in ("p", "p2", "k"))
    return held.crossJoin(F.broadcast(p.crossJoin(p2).crossJoin(k).where("k <= p")))


@query(f"WITH {_GRID} SELECT worker, CAST(p AS INTEGER) AS p, CAST(p2 AS INTEGER) AS p2, CAST(k AS INTEGER) AS k, CAST((((k - 1) * rows // p + 1) * p2 + rows - 1) // rows AS INTEGER) AS j FROM grid")
def translate_index(spark, d):
    j = P.translate_col(F.col("rows"), F.col("p"), F.col("p2"), F.col("k"))
    return grid(spark, d).select("worker", *[F.col(c).cast("int").alias(c) for c in ("p", "p2", "k")], j.alias("j"))


@query(f"""WITH RECURSIVE {_GRID}, moved AS (SELECT worker, rows, p, p2, k AS k0, k % p + 1 AS k FROM grid),
walk AS (
  SELECT worker, rows, p, p2, k0, k, (((k - 1) * rows // p + 1) * p2 + rows - 1) // rows AS j FROM moved
  UNION ALL
  SELECT worker, rows, p, p2, k0, CASE WHEN j = 1 THEN 1 ELSE (((j - 2) * rows // p2 + 1) * p + rows - 1) // rows END, greatest(j - 1, 1) FROM walk WHERE (k - 1) * rows // p <> (j - 1) * rows // p2)
SELECT worker, CAST(p AS INTEGER) AS p, CAST(p2 AS INTEGER) AS p2, CAST(k0 AS INTEGER) AS k, CAST(j AS INTEGER) AS j FROM walk WHERE (k - 1) * rows // p = (j - 1) * rows // p2""")
def align_index(spark, d):
    """The alignment walk for every worker and a grid of counts, as a recursive query."""
    written(grid(spark, d), "align").createOrReplaceTempView("align_grid")  # the lines are counted once, not at every step
    return spark.sql("""
      WITH RECURSIVE walk(worker, rows, p, p2, k0, k, j) AS (
        SELECT worker, rows, p, p2, k, k % p + 1, (((k % p) * rows DIV p + 1) * p2 + rows - 1) DIV rows FROM align_grid
        UNION ALL
        SELECT worker, rows, p, p2, k0, IF(j = 1, 1L, (((j - 2) * rows DIV p2 + 1) * p + rows - 1) DIV rows), greatest(j - 1, 1L)
        FROM walk WHERE (k - 1) * rows DIV p <> (j - 1) * rows DIV p2)
      SELECT worker, CAST(p AS INT) AS p, CAST(p2 AS INT) AS p2, CAST(k0 AS INT) AS k, CAST(j AS INT) AS j FROM walk WHERE (k - 1) * rows DIV p = (j - 1) * rows DIV p2""")


@query(f"WITH {BLOCKS} SELECT worker, CAST(t AS INTEGER) AS t, CAST((t - 1) % 10 + 1 AS INTEGER) AS k, first_row - 1 + ((t - 1) % 10) * (last_row - first_row + 1) // 10 + 1 AS lo FROM blocks, range(1, 26) AS r(t)")
def cyclic_visits(spark, d):
    visits = layout(spark, d).withColumn("t", F.explode(F.sequence(F.lit(1), F.lit(25)))).withColumn("k", F.pmod(F.col("t") - 1, F.lit(10)) + 1)
    lo, _ = P.sub_bounds_col(F.col("rows"), F.lit(10), F.col("k"))
    return visits.select("worker", "t", "k", (F.col("first_row") - 1 + lo).alias("lo"))


@query(f"""WITH {TRACE}, a AS (SELECT DISTINCT worker FROM trace WHERE comp_ms > 1300), b AS (SELECT DISTINCT worker FROM trace WHERE comm_ms < 0.2)
SELECT 'both' AS what, worker FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'only_slow', worker FROM (SELECT * FROM a EXCEPT SELECT * FROM b)""")
def participants_setops(spark, d):
    tr = trace(spark, d)
    a, b = tr.where("comp_ms > 1300").select("worker"), tr.where("comm_ms < 0.2").select("worker")
    return a.intersect(b).select(F.lit("both").alias("what"), "worker").unionByName(a.exceptAll(b).distinct().join(b.distinct(), "worker", "left_anti").select(F.lit("only_slow").alias("what"), "worker"))


@query(f"""WITH {TRACE}, r AS (SELECT worker, t, rank() OVER (PARTITION BY t ORDER BY round_trip_ms, worker) AS r FROM trace)
SELECT DISTINCT worker FROM trace WHERE worker NOT IN (SELECT worker FROM r WHERE r <= 1)""")
def never_fresh_workers(spark, d):
    """Workers never the fastest of any iteration."""
    tr = trace(spark, d)
    rank = F.rank().over(Window.partitionBy("t").orderBy("round_trip_ms", "worker"))
    fresh = tr.withColumn("r", rank).where("r <= 1").select("worker").distinct()
    return tr.select("worker").distinct().join(fresh, "worker", "left_anti")
