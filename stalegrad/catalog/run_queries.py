"""Whole runs over recorded latencies, their measures, and one SQL oracle for all methods.

The schedule of a run with fixed pieces needs no cache replay in SQL: pieces are
disjoint and a worker's results arrive in the order of their versions, so the
cache holds the newest arrival of each piece.  The oracle walks the quorum loop
as a recursive query over list-valued state, derives the arrivals, and steps the
iterate in a second recursion that recomputes every cached subgradient at the
version it was made from.
"""

from __future__ import annotations

from dataclasses import replace
from functools import partial

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from stalegrad.catalog.latency_queries import N, trace
from stalegrad.catalog.optimiser_queries import LOGIT
from stalegrad.operators import gradients as G
from stalegrad.operators import matrix as M
from stalegrad.operators import metrics
from stalegrad.plans import workloads
from stalegrad.plans.loop import Options, delivery_log, plan, run, trace_latency
from stalegrad.sources.tables import load

QUERIES, ORACLES = {}, {}
RAMP, MARGIN, PARTS = 0.4, 0.02, 10
STEPS = {"logistic": (60, 10), "pca": (30, 5)}  # iterations, measured every
COLUMNS, COMPONENTS = 128, 3


def query(name: str, f, sql: str | None = None) -> None:
    f.__name__ = name
    QUERIES[name] = f
    if sql:
        ORACLES[name] = sql


# --- the schedule ----------------------------------------------------------------------------

_ZERO = "[" + ", ".join(["0.0"] * N) + "]"
_IDLE = "[" + ", ".join(["0"] * N) + "]"


def schedule_sql(n: str, method: str, w: int, iterations: int) -> str:
    """CTEs walk (ends), arr (arrivals) and entries (the cache after each iteration); ``n`` is the row count as SQL."""
    full = method == "gd"
    p = 1 if full else PARTS
    size = f"(((jobs[i] % {p}) + 1) * s.rows[i] // {p} - (jobs[i] % {p}) * s.rows[i] // {p})"
    cost = f"+ l.cm[i][(jobs[i] % l.len) + 1] + l.cp[i][(jobs[i] % l.len) + 1] * ({size} / (s.rows[i] / {PARTS}))"
    margin = "q" if full else f"greatest(q, now + CAST('{1 + MARGIN}' AS DOUBLE) * (q - now))"
    kept = {"stale_cache": "true"}.get(method, "arrived = version")
    held = "a.arrived = st.t" if method in ("sgd", "gd") else "a.arrived <= st.t"
    return f"""trace AS (
  SELECT CAST(user_id % {N} + 1 AS INTEGER) AS worker, row_number() OVER (PARTITION BY user_id % {N} ORDER BY ts, event_id) AS t,
         CAST(json_extract_string(props, '$.k') AS DOUBLE) / 10 + 0.1 AS comm_ms, (1000.0 + value) * (1 + CAST('{RAMP}' AS DOUBLE) * (user_id % {N} + 1) / {N}) AS comp_ms FROM events),
len AS (SELECT min(c) AS len FROM (SELECT count(*) AS c FROM trace GROUP BY worker)),
lat AS (SELECT list(cm ORDER BY worker) AS cm, list(cp ORDER BY worker) AS cp, any_value(len) AS len FROM (SELECT worker, any_value(len) AS len, list(comm_ms ORDER BY t) AS cm, list(comp_ms ORDER BY t) AS cp FROM trace, len WHERE t <= len GROUP BY worker)),
blocks AS (SELECT CAST(w AS INTEGER) AS worker, (w - 1) * {n} // {N} AS before, w * {n} // {N} - (w - 1) * {n} // {N} AS rows FROM range(1, {N + 1}) AS r(w)),
shape AS (SELECT list(rows ORDER BY worker) AS rows FROM blocks),
walk AS (
  SELECT 0 AS t, CAST(0 AS DOUBLE) AS now, CAST({_ZERO} AS DOUBLE[]) AS free, CAST({_IDLE} AS BIGINT[]) AS jobs, CAST({_IDLE} AS BIGINT[]) AS was, CAST([] AS DOUBLE[]) AS beg, CAST([] AS DOUBLE[]) AS done, CAST(0 AS DOUBLE) AS e
  UNION ALL
  SELECT t, e, list_transform(range(1, {N + 1}), lambda i: CASE WHEN beg[i] < e OR done[i] <= e THEN done[i] ELSE free[i] END),
         list_transform(range(1, {N + 1}), lambda i: CASE WHEN beg[i] < e OR done[i] <= e THEN jobs[i] + 1 ELSE jobs[i] END), jobs, beg, done, e
  FROM (SELECT t, free, jobs, beg, done, {margin} AS e
        FROM (SELECT t, now, free, jobs, beg, done, list_sort(done)[{N if full else w}] AS q
              FROM (SELECT walk.t + 1 AS t, now, free, jobs, list_transform(range(1, {N + 1}), lambda i: greatest(now, free[i])) AS beg,
                           list_transform(range(1, {N + 1}), lambda i: greatest(now, free[i]) {cost}) AS done
                    FROM walk, lat l, shape s WHERE walk.t < {iterations})))),
steps AS (SELECT t, e FROM walk WHERE t > 0),
tasks AS (SELECT t AS version, CAST(i AS INTEGER) AS worker, was[i] % {p} + 1 AS k, beg[i] AS started, done[i] AS finish FROM walk, range(1, {N + 1}) AS r(i) WHERE t > 0 AND (beg[i] < e OR done[i] <= e)),
came AS (SELECT version, tasks.worker, k, started, finish, (SELECT min(steps.t) FROM steps WHERE steps.e >= finish) AS arrived, before + (k - 1) * rows // {p} + 1 AS lo, before + k * rows // {p} AS hi FROM tasks JOIN blocks ON blocks.worker = tasks.worker),
log AS (SELECT *, arrived = version AS fresh, {kept} AS used FROM came WHERE arrived IS NOT NULL),
entries AS (SELECT st.t, a.worker, a.k, a.lo, a.hi, max(a.version) AS version FROM steps st JOIN log a ON {held} AND a.used GROUP BY st.t, a.worker, a.k, a.lo, a.hi),
state AS (SELECT t, count(*) AS cache_entries, sum(hi - lo + 1) / {n} AS xi FROM entries GROUP BY t),
counts AS (SELECT arrived AS t, count(*) FILTER (WHERE fresh) AS n_fresh, count(*) FILTER (WHERE NOT fresh) AS n_stale FROM log WHERE used GROUP BY arrived)"""


def latencies(spark, d):
    """Recorded latencies by (task, worker) of the tasks that every worker has."""
    rows = trace(spark, d, ramp=RAMP).groupBy("t").agg(F.array_sort(F.collect_list(F.struct("worker", "comm_ms", "comp_ms"))).alias("x")).where(F.size("x") == N)
    most = max(it for it, _ in STEPS.values())  # no worker begins more tasks than there are iterations
    got = rows.where(F.col("t") <= most).orderBy("t").collect()
    return trace_latency(np.array([[x["comm_ms"] for x in r["x"]] for r in got]), np.array([[x["comp_ms"] for x in r["x"]] for r in got]))


def options(method: str, w: int, kind: str) -> Options:
    return Options(method=method, w=N if method == "gd" else w, iterations=STEPS[kind][0], parts=PARTS, eta=1.0 if method == "gd" else workloads.ETA[kind], margin=MARGIN)


def logs(spark, d, method: str = "stale_cache", w: int = 3) -> DataFrame:
    """The delivery log of a run on the logistic rows."""
    n = load(spark, d, "lineitem").count()
    return spark.createDataFrame(delivery_log(plan(n, N, latencies(spark, d), options(method, w, "logistic"))))


def ends(spark, d, method: str, w: int) -> DataFrame:
    n = load(spark, d, "lineitem").count()
    return spark.createDataFrame([(t + 1, float(e)) for t, e in enumerate(plan(n, N, latencies(spark, d), options(method, w, "logistic")).ends)], "t int, end_ms double")


# --- the runs ----------------------------------------------------------------------------------

_SHOWN = "t int, time_ms double, objective double, coverage double, cache_entries int, n_fresh int, n_stale int"


def traced(spark, d, method: str, w: int, kind: str, limit: int | None = None, steps: tuple[int, int] | None = None) -> DataFrame:
    """A run over recorded latencies by the kernel that fits the matrix; ``steps``: iterations, measured every."""
    steps = steps or STEPS[kind]
    kernel, objective, _ = workloads.problem(spark, d, kind, columns=COLUMNS, limit=limit, optimum=False)
    o = replace(options(method, w, kind), iterations=steps[0])
    out = run(kernel, objective, plan(objective.n, N, latencies(spark, d), o), o, every=steps[1])
    shown = spark.createDataFrame(out.drop(columns="gap"), _SHOWN)
    return shown.select("t", F.round("time_ms", 6).alias("time_ms"), F.round("objective", 9).alias("objective"), F.round("coverage", 9).alias("coverage"), "cache_entries", "n_fresh", "n_stale")


_FIELDS = """CAST(o.t AS INTEGER) AS t, round(coalesce(steps.e, 0.0), 6) AS time_ms, round(o.objective, 9) AS objective, round(coalesce(state.xi, 0.0), 9) AS coverage,
CAST(coalesce(cache_entries, 0) AS INTEGER) AS cache_entries, CAST(coalesce(n_fresh, 0) AS INTEGER) AS n_fresh, CAST(coalesce(n_stale, 0) AS INTEGER) AS n_stale
FROM objectives o LEFT JOIN steps ON steps.t = o.t LEFT JOIN state ON state.t = o.t LEFT JOIN counts ON counts.t = o.t"""


def _piece_rows(table: str, method: str) -> str:
    """Rows of ``table`` with the piece that holds them."""
    p = 1 if method == "gd" else PARTS
    return f"SELECT {table}.*, worker, ((sample_idx - before) * {p} + rows - 1) // rows AS k FROM {table} JOIN blocks ON sample_idx > before AND sample_idx <= before + rows"


def logistic_ctes(method: str, w: int, steps: tuple[int, int] | None = None) -> str:
    iterations, every = steps or STEPS["logistic"]
    eta = 1.0 if method == "gd" else workloads.ETA["logistic"]
    z = " + ".join(f"v{i} * x{i}" for i in range(7))
    grads = ", ".join(f"sum(-label / (1 + exp(label * ({z}))) / n * x{i}) AS g{i}" for i in range(7))
    stepped = ", ".join(f"vs[t + 1][{i + 1}] - CAST('{eta}' AS DOUBLE) * (g{i} / xi + vs[t + 1][{i + 1}] / n)" for i in range(7))
    return f"""{LOGIT.replace('m AS (', 'm AS MATERIALIZED (')}, {schedule_sql("(SELECT count(*) FROM lineitem)", method, w, iterations)},
mp AS MATERIALIZED ({_piece_rows('m', method)}),
run AS (
  SELECT CAST(0 AS BIGINT) AS t, CAST([[{', '.join(['0.0'] * 7)}]] AS DOUBLE[][]) AS vs
  UNION ALL
  SELECT t + 1, list_append(vs, [{stepped}])
  FROM (SELECT t, any_value(vs) AS vs, any_value(xi) AS xi, any_value(n) AS n, {grads}
        FROM (SELECT run.t, vs, st.xi, e.worker, e.k, {', '.join(f'vs[e.version][{i + 1}] AS v{i}' for i in range(7))} FROM run JOIN entries e ON e.t = run.t + 1 JOIN state st ON st.t = run.t + 1) held
        JOIN mp ON mp.worker = held.worker AND mp.k = held.k GROUP BY t)),
final AS (SELECT vs FROM run ORDER BY t DESC LIMIT 1),
iterates AS (SELECT t, {', '.join(f'vs[t + 1][{i + 1}] AS v{i}' for i in range(7))} FROM final, range(0, {iterations + 1}) AS r(t)),
everywhere AS (SELECT i.t, sum(ln(1 + exp(-label * ({z})))) / max(n) + any_value({' + '.join(f'v{i} * v{i}' for i in range(7))}) / (2 * max(n)) AS objective FROM iterates i, m WHERE i.t % {every} = 0 GROUP BY i.t),
objectives AS (SELECT * FROM everywhere)"""


_START = f"(CAST('0x' || substr(md5('0|' || c || '|' || j), 1, 12) AS BIGINT) + 0.5) / 281474976710656.0 - 0.5"
_DOT = "list_inner_product"


def _orthonormal(a: str, source: str, carry: str) -> str:
    """Gram-Schmidt of three lists a1..a3 of ``source``."""
    scale = lambda x, norm: f"list_transform({x}, lambda y: y / {norm})"
    less = lambda x, q, by: f"list_transform(range(1, len({x}) + 1), lambda i: {x}[i] - {by} * {q}[i])"
    first = f"SELECT {carry}, {scale(f'{a}1', f'sqrt({_DOT}({a}1, {a}1))')} AS q1, {a}2, {a}3 FROM {source}"
    second = f"SELECT {carry}, q1, {scale('b', f'sqrt({_DOT}(b, b))')} AS q2, {a}3 FROM (SELECT {carry}, q1, {less(f'{a}2', 'q1', f'{_DOT}(q1, {a}2)')} AS b, {a}3 FROM ({first}))"
    twice = f"list_transform(range(1, len({a}3) + 1), lambda i: {a}3[i] - {_DOT}(q1, {a}3) * q1[i] - {_DOT}(q2, {a}3) * q2[i])"
    return f"SELECT {carry}, q1, q2, {scale('b', f'sqrt({_DOT}(b, b))')} AS q3 FROM (SELECT {carry}, q1, q2, {twice} AS b FROM ({second}))"


def pca_ctes(method: str, w: int) -> str:
    iterations, every = STEPS["pca"]
    eta = 1.0 if method == "gd" else workloads.ETA["pca"]
    # a step of one is a power step without rounding of v - v
    stepped = ", ".join(f"list(h.v{c} - CAST('{eta}' AS DOUBLE) * (h.h{c} / h.xi + h.v{c}) ORDER BY h.col) AS a{c}" for c in (1, 2, 3))
    return f"""cells AS MATERIALIZED (SELECT DISTINCT doc_id, CAST(CAST('0x' || substr(md5(tok), 1, 8) AS BIGINT) % {COLUMNS} AS INTEGER) AS col FROM (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[a-z0-9]+')) AS tok FROM documents)),
ids AS (SELECT doc_id, row_number() OVER (ORDER BY md5('0|' || doc_id), doc_id) AS sample_idx FROM (SELECT DISTINCT doc_id FROM cells)),
nz AS MATERIALIZED (SELECT sample_idx, col FROM cells JOIN ids USING (doc_id)),
{schedule_sql("(SELECT count(*) FROM ids)", method, w, iterations)},
np AS MATERIALIZED ({_piece_rows('nz', method)}),
raw AS (SELECT list(u ORDER BY c) FILTER (WHERE j = 0) AS a1, list(u ORDER BY c) FILTER (WHERE j = 1) AS a2, list(u ORDER BY c) FILTER (WHERE j = 2) AS a3 FROM (SELECT c, j, {_START} AS u FROM range(0, {COLUMNS}) AS x(c), range(0, 3) AS y(j))),
run AS (
  SELECT t, [[q1, q2, q3]] AS vs FROM ({_orthonormal('a', 'raw', 'CAST(0 AS BIGINT) AS t').replace('SELECT CAST(0 AS BIGINT) AS t, q1', 'SELECT t, q1').replace('SELECT CAST(0 AS BIGINT) AS t, list_transform(b', 'SELECT t, list_transform(b')})
  UNION ALL
  SELECT t + 1, list_append(vs, [q1, q2, q3]) FROM ({_orthonormal('a', f'''(
    SELECT h.t, any_value(h.vs) AS vs, {stepped} FROM (
      SELECT cur.t, cur.vs, cur.xi, x.col, cur.vs[cur.t + 1][1][x.col + 1] AS v1, cur.vs[cur.t + 1][2][x.col + 1] AS v2, cur.vs[cur.t + 1][3][x.col + 1] AS v3, coalesce(g.h1, 0) AS h1, coalesce(g.h2, 0) AS h2, coalesce(g.h3, 0) AS h3
      FROM (SELECT run.t, run.vs, st.xi FROM run JOIN state st ON st.t = run.t + 1) cur CROSS JOIN range(0, {COLUMNS}) AS x(col)
      LEFT JOIN (SELECT nz.col, -sum(p.a1) AS h1, -sum(p.a2) AS h2, -sum(p.a3) AS h3 FROM (
          SELECT nz.sample_idx, sum(held.v1[nz.col + 1]) AS a1, sum(held.v2[nz.col + 1]) AS a2, sum(held.v3[nz.col + 1]) AS a3
          FROM (SELECT e.worker, e.k, run.vs[e.version][1] AS v1, run.vs[e.version][2] AS v2, run.vs[e.version][3] AS v3 FROM run JOIN entries e ON e.t = run.t + 1) held
          JOIN np AS nz ON nz.worker = held.worker AND nz.k = held.k GROUP BY nz.sample_idx) p JOIN nz ON nz.sample_idx = p.sample_idx GROUP BY nz.col) g ON g.col = x.col) h GROUP BY h.t)''', 't, vs')})),
final AS (SELECT vs FROM run ORDER BY t DESC LIMIT 1),
projected AS (SELECT r.t, nz.sample_idx, sum(vs[r.t + 1][1][col + 1]) AS a1, sum(vs[r.t + 1][2][col + 1]) AS a2, sum(vs[r.t + 1][3][col + 1]) AS a3 FROM final, range(0, {iterations + 1}, {every}) AS r(t), nz GROUP BY r.t, nz.sample_idx),
objectives AS (SELECT t, -sum(a1 * a1 + a2 * a2 + a3 * a3) / (SELECT count(*) FROM nz) AS objective FROM projected GROUP BY t)"""


METHODS = [("stale_cache", 3), ("avg_gradient", 8), ("avg_gradient", 3), ("sgd", 3), ("gd", 8)]
for _m, _w in METHODS:
    query(f"run_{_m}_w{_w}_logistic", partial(traced, method=_m, w=_w, kind="logistic"), f"WITH RECURSIVE {logistic_ctes(_m, _w)} SELECT {_FIELDS}")
    query(f"run_{_m}_w{_w}_pca", partial(traced, method=_m, w=_w, kind="pca"), f"WITH RECURSIVE {pca_ctes(_m, _w)} SELECT {_FIELDS}")
query("run_sc_logistic", partial(traced, method="stale_cache", w=3, kind="logistic", limit=0, steps=(30, 6)), f"WITH RECURSIVE {logistic_ctes('stale_cache', 3, (30, 6))} SELECT {_FIELDS}")


# --- measures over the log of one run ------------------------------------------------------------

_L = STEPS["logistic"][0]
_ROWS = "(SELECT count(*) FROM lineitem)"
_LOG = f"""{schedule_sql(_ROWS, 'stale_cache', 3, _L)},
acted AS (SELECT *, CASE WHEN row_number() OVER (PARTITION BY worker, k ORDER BY version) = 1 THEN 'insert' ELSE 'replace' END AS action, row_number() OVER (ORDER BY arrived, finish, worker) - 1 AS seq FROM log)"""


def _i(*names: str) -> str:
    return ", ".join(f"CAST({n} AS INTEGER) AS {n}" for n in names)


def delivery_log_traced(spark, d):
    """Every arrival with its interval, times, freshness and cache action."""
    return logs(spark, d).select(*[F.col(c).cast("int").alias(c) for c in ("worker", "version", "arrived_in", "k")], "lo", "hi", F.round("started_ms", 6).alias("started_ms"), F.round("finished_ms", 6).alias("finished_ms"), "fresh", "action")


query("delivery_log_traced", delivery_log_traced, f"WITH RECURSIVE {_LOG} SELECT {_i('worker', 'version')}, CAST(arrived AS INTEGER) AS arrived_in, {_i('k')}, lo, hi, round(started, 6) AS started_ms, round(finish, 6) AS finished_ms, fresh, action FROM acted")
_SHARES = f"shares AS (SELECT worker, sum(CASE WHEN fresh THEN 1.0 ELSE 0.0 END) / {_L}.0 AS u FROM log GROUP BY worker)"
query("participation", lambda spark, d: metrics.participation(logs(spark, d), _L).select(F.col("worker").cast("int").alias("worker"), F.round("u", 9).alias("u")), f"WITH RECURSIVE {_LOG}, {_SHARES} SELECT {_i('worker')}, round(u, 9) AS u FROM shares")
query("participation_spread", lambda spark, d: metrics.participation_spread(metrics.participation(logs(spark, d), _L)).select(F.round("spread", 9).alias("spread"), F.round("sd", 9).alias("sd")), f"WITH RECURSIVE {_LOG}, {_SHARES} SELECT round(max(u) - min(u), 9) AS spread, round(stddev_pop(u), 9) AS sd FROM shares")
query("within_margin", lambda spark, d: metrics.within_margin(logs(spark, d), 3).select(F.col("arrived_in").cast("int").alias("arrived_in"), "extra"), f"WITH RECURSIVE {_LOG} SELECT CAST(arrived AS INTEGER) AS arrived_in, count(*) FILTER (WHERE fresh) - 3 AS extra FROM log GROUP BY arrived")


def health(spark, d) -> DataFrame:
    return metrics.cache_health(logs(spark, d), load(spark, d, "lineitem").count())


_HEALTH = f"{_LOG}, health AS (SELECT seq, arrived, action, CASE WHEN action = 'replace' THEN 1 ELSE 0 END AS n_evicted, sum(CASE WHEN action = 'insert' THEN hi - lo + 1 ELSE 0 END) OVER (ORDER BY seq) AS rows_covered FROM acted)"
query("cache_health", lambda spark, d: health(spark, d).select(F.col("seq").cast("int").alias("seq"), F.col("arrived_in").cast("int").alias("arrived_in"), "action", F.col("n_evicted").cast("int").alias("n_evicted"), "rows_covered", F.round("coverage", 9).alias("coverage")),
      f"WITH RECURSIVE {_HEALTH} SELECT {_i('seq')}, CAST(arrived AS INTEGER) AS arrived_in, action, {_i('n_evicted')}, CAST(rows_covered AS BIGINT) AS rows_covered, round(rows_covered / {_ROWS}, 9) AS coverage FROM health")
query("eviction_cost", lambda spark, d: metrics.eviction_cost(health(spark, d), load(spark, d, "lineitem").count(), 1).select(F.col("missing_row_iterations").cast("long").alias("missing_row_iterations")),
      f"WITH RECURSIVE {_HEALTH}, ended AS (SELECT arrived, max(rows_covered) AS r FROM health GROUP BY arrived) SELECT CAST(sum({_ROWS} - r) AS BIGINT) AS missing_row_iterations FROM ended")
query("work_done", lambda spark, d: metrics.work(logs(spark, d), 7, 1).select("action", F.col("operations").cast("long").alias("operations"), "tasks"), f"WITH RECURSIVE {_LOG} SELECT action, CAST(sum(14 * (hi - lo + 1)) AS BIGINT) AS operations, count(*) AS tasks FROM acted GROUP BY action")
query("staleness_by_action", lambda spark, d: metrics.staleness_histogram(logs(spark, d)).select(F.col("staleness").cast("int").alias("staleness"), "action", "n"), f"WITH RECURSIVE {_LOG} SELECT CAST(arrived - version AS INTEGER) AS staleness, action, count(*) AS n FROM acted GROUP BY 1, 2")
query("iteration_latency", lambda spark, d: metrics.iteration_latency(ends(spark, d, "stale_cache", 3)).select("t", F.round("end_ms", 6).alias("end_ms"), F.round("latency_ms", 6).alias("latency_ms")),
      f"WITH RECURSIVE {_LOG} SELECT {_i('t')}, round(e, 6) AS end_ms, round(e - lag(e, 1, 0.0) OVER (ORDER BY t), 6) AS latency_ms FROM steps")
query("balance_gain", lambda spark, d: metrics.balance_gain(ends(spark, d, "avg_gradient", 8), ends(spark, d, "stale_cache", 3), 20).select(*[F.round(c, 6).alias(c) for c in ("plain_ms", "balanced_ms", "gain")]),
      "SELECT round(a.ms, 6) AS plain_ms, round(b.ms, 6) AS balanced_ms, round(a.ms / b.ms, 6) AS gain FROM " + ", ".join(f"(WITH RECURSIVE {schedule_sql(_ROWS, m, w, _L)} SELECT (max(e) - max(e) FILTER (WHERE t <= {_L - 20})) / 20 AS ms FROM steps) AS {x}" for x, m, w in (("a", "avg_gradient", 8), ("b", "stale_cache", 3))))


# --- measures over trajectories --------------------------------------------------------------------

_PAIR = [("stale_cache", 3), ("sgd", 3)]
_BOTH = "runs AS (" + " UNION ALL ".join(f"SELECT '{m}' AS method, {i} AS run_id, t, time_ms, objective AS gap FROM (WITH RECURSIVE {logistic_ctes(m, w)} SELECT {_FIELDS})" for i, (m, w) in enumerate(_PAIR)) + ")"
GRID = [5000.0, 15000.0, 40000.0, 90000.0]


def trajectories(spark, d) -> DataFrame:
    """Two recorded runs, the objective in the place of the gap."""
    out = None
    for i, (m, w) in enumerate(_PAIR):
        part = traced(spark, d, m, w, "logistic").select(F.lit(m).alias("method"), F.lit(i).alias("run_id"), "t", "time_ms", F.col("objective").alias("gap"))
        out = part if out is None else out.unionByName(part)
    return out


query("plateau", lambda spark, d: metrics.plateau(trajectories(spark, d), 3), f"WITH {_BOTH}, r AS (SELECT *, row_number() OVER (PARTITION BY method ORDER BY t DESC) AS n FROM runs) SELECT method, min(gap) AS floor FROM r WHERE n <= 3 GROUP BY method")
query("rate", lambda spark, d: metrics.rate(trajectories(spark, d)).select("method", F.round("slope", 9).alias("slope")), f"WITH {_BOTH} SELECT method, round(regr_slope(ln(gap), t), 9) AS slope FROM runs WHERE gap > 0 GROUP BY method")
query("rate_by_phase", lambda spark, d: metrics.rate_by_phase(trajectories(spark, d).where("method = 'stale_cache'"), [20, 40]).select("phase", F.round("slope", 9).alias("slope")),
      f"WITH {_BOTH} SELECT CAST((t > 20)::INT + (t > 40)::INT AS INTEGER) AS phase, round(regr_slope(ln(gap), t), 9) AS slope FROM runs WHERE method = 'stale_cache' GROUP BY 1")
_GRID = "grid(g) AS (VALUES " + ", ".join(f"(CAST({g} AS DOUBLE))" for g in GRID) + ")"
_LAST = f"{_BOTH}, {_GRID}, held AS (SELECT method, g, arg_max(gap, time_ms) AS gap FROM runs, grid WHERE time_ms <= g GROUP BY method, g)"
query("mean_trajectory", lambda spark, d: metrics.mean_trajectory(trajectories(spark, d).withColumn("method", F.lit("all")), GRID).select("method", "time_ms", F.round("gap", 9).alias("gap"), "runs"), f"WITH {_LAST} SELECT 'all' AS method, g AS time_ms, round(avg(gap), 9) AS gap, count(*) AS runs FROM held GROUP BY g")
query("precision_loss", lambda spark, d: metrics.lb_precision_loss(*[trajectories(spark, d).where(F.col("method") == m) for m, _ in _PAIR], GRID).select("time_ms", F.round("loss", 9).alias("loss")),
      f"WITH {_LAST} SELECT a.g AS time_ms, round(b.gap - a.gap, 9) AS loss FROM held a JOIN held b ON a.g = b.g AND a.method = 'stale_cache' AND b.method = 'sgd'")
query("speedup", lambda spark, d: metrics.speedup(metrics.time_to_gap(trajectories(spark, d), [0.6, 0.5, 0.45]), "stale_cache", "sgd").select("eps", F.round("speedup", 6).alias("speedup")),
      f"WITH {_BOTH}, eps(eps) AS (VALUES (CAST(0.6 AS DOUBLE)), (CAST(0.5 AS DOUBLE)), (CAST(0.45 AS DOUBLE))), hit AS (SELECT method, eps, min(CASE WHEN gap <= eps THEN time_ms END) AS ms FROM runs, eps GROUP BY method, eps) SELECT a.eps, round(b.ms / a.ms, 6) AS speedup FROM hit a JOIN hit b ON a.eps = b.eps AND a.method = 'stale_cache' AND b.method = 'sgd'")
