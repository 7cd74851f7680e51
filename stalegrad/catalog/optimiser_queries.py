"""Queries on the simulator, gradients, cache, balancer and whole runs."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stalegrad.catalog.latency_queries import STATS, TRACE, N, layout, r6, trace
from stalegrad.operators import gradients as G
from stalegrad.operators import latency as L
from stalegrad.operators import matrix as M
from stalegrad.operators import metrics, simulate
from stalegrad.operators import partitioning as P
from stalegrad.operators.cache import IntervalCache
from stalegrad.operators.objectives import Logistic
from stalegrad.plans import workloads
from stalegrad.sources.tables import load

QUERIES, ORACLES = {}, {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


# --- simulation of the quorum loop over recorded latencies -------------------------------

T, W = 40, 3
_ZERO = "[" + ", ".join(["0.0"] * N) + "]"


def _sim_sql(w: int) -> str:
    return f"""lat AS (SELECT t, list(round_trip_ms ORDER BY worker) AS x FROM trace GROUP BY t HAVING count(*) = {N}),
sim AS (
  SELECT 0 AS t, CAST(0 AS DOUBLE) AS now, CAST({_ZERO} AS DOUBLE[]) AS free, CAST([] AS DOUBLE[]) AS beg, CAST([] AS DOUBLE[]) AS done, CAST(0 AS DOUBLE) AS e
  UNION ALL
  SELECT t, e, list_transform(range(1, {N + 1}), lambda i: CASE WHEN beg[i] < e OR done[i] <= e THEN done[i] ELSE free[i] END), beg, done, e
  FROM (SELECT t, free, beg, done, list_sort(done)[{w}] AS e
        FROM (SELECT lat.t, free, list_transform(range(1, {N + 1}), lambda i: greatest(now, free[i])) AS beg,
                     list_transform(range(1, {N + 1}), lambda i: greatest(now, free[i]) + x[i]) AS done
              FROM sim JOIN lat ON lat.t = sim.t + 1)))"""


def whole(spark, d) -> DataFrame:
    """(t, x array<double>): latencies by worker of every iteration that all workers have."""
    rows = trace(spark, d).groupBy("t").agg(F.array_sort(F.collect_list(F.struct("worker", "round_trip_ms"))).alias("x"))
    return rows.where(F.size("x") == N).select("t", F.transform("x", lambda s: s["round_trip_ms"]).alias("x"))


@query(f"WITH RECURSIVE {TRACE}, {_sim_sql(W)} SELECT CAST(t AS INTEGER) AS t, round(e, 3) AS end_ms, CAST(len(list_filter(done, lambda x: x <= e)) AS INTEGER) AS n_fresh FROM sim WHERE t > 0")
def sim_iterations(spark, d):
    return simulate.stream(whole(spark, d), W).select(F.col("t").cast("int").alias("t"), F.round("end_ms", 3).alias("end_ms"), F.size(F.filter("fresh", lambda hit: hit)).alias("n_fresh"))


def fresh_of(spark, d) -> DataFrame:
    return simulate.fresh_fraction(simulate.stream(whole(spark, d), W)).select(F.col("worker").cast("int").alias("worker"), "u")


@query(f"""WITH RECURSIVE {TRACE}, {_sim_sql(W)}, flat AS (SELECT CAST(i AS INTEGER) AS worker, done[i] <= e AS hit FROM sim, range(1, {N + 1}) AS r(i) WHERE t > 0)
SELECT worker, round(avg(CASE WHEN hit THEN 1.0 ELSE 0.0 END), 6) AS u FROM flat GROUP BY worker""")
def fresh_fraction(spark, d):
    return fresh_of(spark, d).select("worker", *r6("u"))


@query(f"""WITH RECURSIVE {TRACE}, {_sim_sql(W)}, tasks AS (SELECT t AS version, done[i] AS finish FROM sim, range(1, {N + 1}) AS r(i) WHERE t > 0 AND (beg[i] < e OR done[i] <= e)),
ends AS (SELECT t, e FROM sim WHERE t > 0),
came AS (SELECT version, ends.t AS arrived FROM tasks ASOF JOIN ends ON ends.e >= tasks.finish)
SELECT CAST(arrived - version AS INTEGER) AS staleness, count(*) AS n FROM came GROUP BY 1""")
def staleness_hist(spark, d):
    late = simulate.stream(whole(spark, d), W).select(F.explode("staleness").alias("staleness"))
    return late.groupBy(F.col("staleness").cast("int").alias("staleness")).agg(F.count(F.lit(1)).alias("n"))


@query(f"""WITH RECURSIVE {TRACE}, {_sim_sql(W)}, os AS (SELECT t, sum(list_sort(x)[{W}]) OVER (ORDER BY t) AS blind FROM lat)
SELECT CAST(t AS INTEGER) AS t, round(e, 3) AS cum_ms, round(blind, 3) AS blind_ms FROM sim JOIN os USING (t)""")
def cumulative_latency(spark, d):
    """Ends of iterations beside the prediction that forgets busy workers."""
    return simulate.stream(whole(spark, d), W).select(F.col("t").cast("int").alias("t"), F.round("end_ms", 3).alias("cum_ms"), F.round("blind_ms", 3).alias("blind_ms"))


@query(" UNION ALL ".join(f"SELECT * FROM (WITH RECURSIVE {TRACE}, {_sim_sql(w)} SELECT {w} AS w, round((SELECT max(e) FROM sim) / (SELECT sum(list_sort(x)[{w}]) FROM lat), 6) AS ratio)" for w in (1, 3, 8)))
def carryover_gap(spark, d):
    """Simulated over carry-over-blind time: above 1 for w < N, 1 for w = N."""
    out = None
    for w in (1, 3, 8):
        last = simulate.stream(whole(spark, d), w).agg(F.max("end_ms").alias("end"), F.max("blind_ms").alias("blind"))
        part = last.select(F.lit(w).alias("w"), F.round(F.col("end") / F.col("blind"), 6).alias("ratio"))
        out = part if out is None else out.unionByName(part)
    return out


@query()
def sim_gamma_replicates(spark, d):
    """Monte-Carlo ends from the fitted gammas (replicates over tasks)."""
    stats = L.worker_stats(trace(spark, d))
    return simulate.cumulative_latency(simulate.simulate(spark, stats, W, T, 64, seed=2)).select("t", *r6("cum_ms"))


# --- matrices and gradients ------------------------------------------------------------

_COLS = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "p_size", "p_retailprice"]
_KEY = "md5(concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey))"
LOGIT = f"""raw AS (SELECT l_quantity, l_extendedprice, l_discount, l_tax, CAST(p_size AS DOUBLE) AS p_size, p_retailprice, {_KEY} AS row_key,
  CASE WHEN (l_extendedprice * (1 - l_discount) > 45000) <> (CAST('0x' || substr({_KEY}, 1, 8) AS BIGINT) < 0.1 * 4294967296.0) THEN 1.0 ELSE -1.0 END AS label
  FROM lineitem JOIN part ON l_partkey = p_partkey),
st AS (SELECT {', '.join(f'avg({c}) AS a{i}, stddev_pop({c}) AS s{i}' for i, c in enumerate(_COLS))}, CAST(count(*) AS DOUBLE) AS n FROM raw),
m AS (SELECT row_number() OVER (ORDER BY md5('0|' || row_key), {', '.join(_COLS)}, label) AS sample_idx, CAST(label AS DOUBLE) AS label, n, {', '.join(f'({c} - a{i}) / s{i} AS x{i}' for i, c in enumerate(_COLS))}, 1.0 AS x6 FROM raw, st)"""
FIXED = [0.3, -0.2, 0.1, 0.05, -0.1, 0.2, 0.4]
_Z = " + ".join(f"{v} * x{i}" for i, v in enumerate(FIXED))


def logit(spark, d, keep: bool = False) -> DataFrame:
    return M.logit_matrix(load(spark, d, "lineitem"), load(spark, d, "part"), keep=keep)


@query(f"WITH {LOGIT} " + " UNION ALL ".join(f"SELECT '{c}' AS col, CAST(round(avg({c}) * count(*) * 100) AS BIGINT) AS sum_hundredths, round(stddev_pop({c}), 6) AS sd FROM raw" for c in _COLS))
def standardized_stats(spark, d):
    """Sums and deviations of the raw columns; the sums are exact, whole parts as integers and the rest by itself."""
    raw = M.logit_rows(load(spark, d, "lineitem"), load(spark, d, "part"))
    _, stats = M.standardize(raw, _COLS)
    whole = {c: F.when(F.abs(F.col(c)) < 1e12, F.round(c)).otherwise(0.0) for c in _COLS}
    cells = [x for c in _COLS for x in (F.sum(whole[c].cast("long")).alias(f"w_{c}"), F.sum(F.col(c) - whole[c]).alias(f"r_{c}"), F.count(c).alias(f"n_{c}"))]
    both = stats.crossJoin(F.broadcast(raw.agg(F.count(F.lit(1)).alias("n"), *cells)))  # one row each

    def hundredths(c: str):
        exact = F.col(f"w_{c}") * 100 + F.round(F.col(f"r_{c}") * 100).cast("long")
        return F.when(F.col(f"n_{c}") == F.col("n"), exact).otherwise(F.round(F.col(f"m_{c}") * F.col("n") * 100).cast("long"))

    return both.select(F.inline(F.array(*[F.struct(F.lit(c).alias("col"), hundredths(c).alias("sum_hundredths"), F.round(f"s_{c}", 6).alias("sd")) for c in _COLS])))


@query(f"WITH {LOGIT} SELECT CAST((sample_idx * {N} + n - 1) // n AS INTEGER) AS worker, count(*) AS rows, CAST(sum(CASE WHEN label > 0 THEN sample_idx ELSE 0 END) AS BIGINT) AS positive_ids FROM (SELECT sample_idx, label, CAST(n AS BIGINT) AS n FROM m) GROUP BY 1")
def sample_index(spark, d):
    """Row ids by hash order, summed over the positive rows of each worker."""
    m = logit(spark, d)
    placed = P.assign(m, m.count(), N, 10)
    return placed.groupBy("worker").agg(F.count(F.lit(1)).alias("rows"), F.sum(F.when(F.col("label") > 0, F.col("sample_idx")).otherwise(0)).alias("positive_ids"))


@query(f"WITH {LOGIT} SELECT round(sum(ln(1 + exp(-label * ({_Z})))) / max(n), 9) AS loss FROM m")
def logistic_loss(spark, d):
    m = logit(spark, d)
    n = m.count()
    value = G.ExpressionKernel(m, n).value(Logistic(n, 7, lam=0.0), np.array(FIXED)[:, None])
    return spark.createDataFrame([(round(value, 9),)], "loss double")


_PIECE = f"(w.first_row - 1 + (k - 1) * (w.last_row - w.first_row + 1) // 10 + 1)"


@query(f"""WITH {LOGIT}, blocks AS (SELECT w AS worker, (w - 1) * (SELECT count(*) FROM m) // {N} + 1 AS first_row, w * (SELECT count(*) FROM m) // {N} AS last_row FROM range(1, {N + 1}) AS r(w)),
pieces AS (SELECT {_PIECE} AS lo, w.first_row - 1 + k * (w.last_row - w.first_row + 1) // 10 AS hi FROM blocks w, range(1, 11) AS r(k))
SELECT lo, {', '.join(f'round(sum(-label / (1 + exp(label * ({_Z}))) / n * x{i}), 9) AS g{i}' for i in range(7))} FROM m JOIN pieces ON sample_idx BETWEEN lo AND hi GROUP BY lo""")
def logistic_subgradients(spark, d):
    """All ten pieces of every worker at a fixed iterate, in one job."""
    m = logit(spark, d, keep=True)
    n = m.count()
    tasks = []
    for w in range(1, N + 1):
        lo, hi = P.sub_bounds(n, N, w)
        tasks += [(lo - 1 + a, lo - 1 + b) for a, b in (P.sub_bounds(hi - lo + 1, 10, k) for k in range(1, 11))]
    out = G.ExpressionKernel(m, n).frame(Logistic(n, 7), tasks, np.array(FIXED)[:, None])
    return out.select("lo", *[F.round(f"g{i}", 9).alias(f"g{i}") for i in range(7)])


_GZ = " + ".join(f"v{i} * x{i}" for i in range(7))


def _gd_sql(eta: float, steps: int) -> str:
    step = ", ".join(f"v{i} - {eta} * (sum(-label / (1 + exp(label * ({_GZ}))) / n * x{i}) + v{i} / max(n))" for i in range(7))
    return f"gd AS (SELECT 0 AS t, {', '.join(f'CAST(0 AS DOUBLE) AS v{i}' for i in range(7))} UNION ALL SELECT t + 1, {step} FROM gd, m WHERE t < {steps} GROUP BY t, {', '.join(f'v{i}' for i in range(7))})"


@query(f"WITH RECURSIVE {LOGIT}, {_gd_sql(1.0, 5)} SELECT CAST(t AS INTEGER) AS t, {', '.join(f'round(v{i}, 9) AS v{i}' for i in range(7))} FROM gd")
def logistic_gd_steps(spark, d):
    m = logit(spark, d, keep=True)
    return spark.createDataFrame([(t, *[round(float(x), 9) for x in v[:, 0]]) for t, v, _ in workloads.gd_steps(m, 1.0, 5)], "t int, " + ", ".join(f"v{i} double" for i in range(7)))


_LOSS = f"loss AS (SELECT method, t, sum(ln(1 + exp(-label * ({_GZ})))) / max(n) AS objective FROM (SELECT 'full' AS method, * FROM gd UNION ALL SELECT 'quarter', * FROM gq) g, m GROUP BY method, t)"
_TTG = f"""{LOGIT}, {_gd_sql(1.0, 6)}, {_gd_sql(0.25, 6).replace('gd AS', 'gq AS').replace('FROM gd', 'FROM gq')}, {_LOSS},
times AS (SELECT method, eps, min(CASE WHEN objective <= eps THEN t * 1000.0 END) AS time_ms FROM loss, (VALUES (0.69), (0.6), (0.5)) AS e(eps) GROUP BY method, eps)"""


def _gd_trajectories(spark, d) -> DataFrame:
    m = logit(spark, d, keep=True)
    rows = [(name, t, 1000.0 * t, obj) for name, eta in (("full", 1.0), ("quarter", 0.25)) for t, _, obj in workloads.gd_steps(m, eta, 6)]
    return spark.createDataFrame(rows, "method string, t int, time_ms double, gap double")


@query(f"WITH RECURSIVE {_TTG} SELECT method, CAST(eps AS DOUBLE) AS eps, CAST(time_ms AS DOUBLE) AS time_ms FROM times")
def time_to_gap(spark, d):
    """First time at which the loss of gradient descent passes each level, for two step sizes."""
    return metrics.time_to_gap(_gd_trajectories(spark, d), [0.69, 0.6, 0.5])


@query(f"WITH RECURSIVE {_TTG} SELECT method, CAST(eps AS DOUBLE) AS eps, CAST(avg(time_ms) AS DOUBLE) AS mean_ms, count(time_ms) AS reached FROM times GROUP BY ROLLUP (method, eps)")
def method_rollup(spark, d):
    return metrics.method_rollup(metrics.time_to_gap(_gd_trajectories(spark, d), [0.69, 0.6, 0.5]))


_CELLS = "cells AS (SELECT DISTINCT l_orderkey AS r, p_brand || '/' || p_type AS c FROM lineitem JOIN part ON l_partkey = p_partkey)"


def cells(spark, d) -> DataFrame:
    part = load(spark, d, "part").select("p_partkey", F.concat_ws("/", "p_brand", "p_type").alias("c"), "p_brand")
    return load(spark, d, "lineitem").select(F.col("l_orderkey").alias("r"), "l_partkey").join(part, F.col("l_partkey") == F.col("p_partkey"))


@query(f"WITH {_CELLS} SELECT count(DISTINCT r) AS n_rows, count(DISTINCT c) AS n_cols, count(*) AS nnz, round(count(*) / (count(DISTINCT r) * count(DISTINCT c)), 9) AS density FROM cells")
def indicator_density(spark, d):
    return M.density(cells(spark, d), "r", "c").withColumn("density", F.round("density", 9))


_BRANDS = """b AS (SELECT DISTINCT l_orderkey AS r, p_brand FROM lineitem JOIN part ON l_partkey = p_partkey),
names AS (SELECT p_brand, dense_rank() OVER (ORDER BY p_brand) AS c FROM (SELECT DISTINCT p_brand FROM b)), nz AS (SELECT r, c FROM b JOIN names USING (p_brand))"""


def brand_cells(spark, d) -> DataFrame:
    return M.indicator_matrix(cells(spark, d), "r", "p_brand").select("r", F.explode("nz").alias("c"))


@query(f"WITH {_BRANDS} SELECT CAST(x.c AS INTEGER) AS i, CAST(y.c AS INTEGER) AS j, count(*) AS val FROM nz x JOIN nz y ON x.r = y.r GROUP BY 1, 2")
def pca_gram(spark, d):
    rows = M.indicator_matrix(cells(spark, d), "r", "p_brand")
    pairs = rows.select(F.explode("nz").alias("i"), "nz").select("i", F.explode("nz").alias("j"))
    return pairs.groupBy("i", "j").agg(F.count(F.lit(1)).alias("val"))


_V = "((c * 7 % 11) - 5) / 10.0"


@query(f"""WITH {_BRANDS}, ids AS (SELECT r, row_number() OVER (ORDER BY md5('0|' || r), r) AS i, count(*) OVER () AS n FROM (SELECT DISTINCT r FROM nz)),
p AS (SELECT r, sum({_V}) AS av FROM nz GROUP BY r)
SELECT CAST((i * {N} + n - 1) // n AS INTEGER) AS worker, CAST(c AS INTEGER) AS col, round(CAST(-sum(av) AS DOUBLE), 6) AS val FROM nz JOIN ids USING (r) JOIN p USING (r) GROUP BY 1, 2""")
def pca_subgradients(spark, d):
    """Subgradients of the indicator matrix by worker at a fixed vector, in coordinate form."""
    rows = M.indicator_matrix(cells(spark, d), "r", "p_brand")
    indexed = M.index_rows(rows, digest=F.md5(F.concat_ws("|", F.lit("0"), F.col("r").cast("string")).cast("binary")))
    placed = P.assign(indexed, indexed.count(), N, 1)
    av = F.aggregate(F.transform("nz", lambda c: (F.pmod(c * 7, F.lit(11)) - 5) / 10.0), F.lit(0.0), lambda a, x: a + x)
    return placed.select("worker", av.alias("av"), F.explode("nz").alias("col")).groupBy("worker", "col").agg(F.round(-F.sum("av"), 6).alias("val"))


@query(f"""WITH {_BRANDS}, p AS (SELECT r, sum({_V}) AS av FROM nz GROUP BY r), w AS (SELECT c, CAST(sum(av) AS DOUBLE) AS y FROM nz JOIN p USING (r) GROUP BY c)
SELECT CAST(c AS INTEGER) AS col, round(y / sqrt((SELECT sum(y * y) FROM w)), 9) AS val FROM w""")
def power_iteration_step(spark, d):
    rows = M.indicator_matrix(cells(spark, d), "r", "p_brand")
    av = F.aggregate(F.transform("nz", lambda c: (F.pmod(c * 7, F.lit(11)) - 5) / 10.0), F.lit(0.0), lambda a, x: a + x)
    y = rows.select(av.alias("av"), F.explode("nz").alias("col")).groupBy("col").agg(F.sum("av").alias("y"))
    norm = y.agg(F.sqrt(F.sum(F.col("y") * F.col("y"))).alias("norm"))
    return y.crossJoin(F.broadcast(norm)).select("col", F.round(F.col("y") / F.col("norm"), 9).alias("val"))


_TOKENS = "SELECT DISTINCT doc_id, CAST(CAST('0x' || substr(md5(tok), 1, 8) AS BIGINT) % 2048 AS INTEGER) AS col FROM (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[a-z0-9]+')) AS tok FROM documents)"


@query(f"SELECT col, count(*) AS docs, min(doc_id) AS first_doc FROM ({_TOKENS}) GROUP BY col")
def token_indicator(spark, d):
    """Column counts of the document indicator matrix."""
    return M.token_cells(spark.read.parquet(f"{d}/documents.parquet")).groupBy("col").agg(F.count(F.lit(1)).alias("docs"), F.min("doc_id").alias("first_doc"))


@query("""SELECT r_name, n_name, count(*) AS rows, round(sum(l_quantity), 2) AS quantity, round(avg(s_acctbal), 6) AS balance
FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name, n_name""")
def supplier_feature_rows(spark, d):
    s, n, r = (spark.read.parquet(f"{d}/{t}.parquet") for t in ("supplier", "nation", "region"))
    small = n.join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 nations, 5 regions
    joined = load(spark, d, "lineitem").join(s.join(F.broadcast(small), F.col("s_nationkey") == F.col("n_nationkey")), F.col("l_suppkey") == F.col("s_suppkey"))
    return joined.groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("rows"), F.round(F.sum("l_quantity"), 2).alias("quantity"), F.round(F.avg("s_acctbal"), 6).alias("balance"))


# --- the cache ----------------------------------------------------------------------------

#: Scripted arrivals of every worker: (seq, pieces, piece, version)
ARRIVALS = [(1, 2, 1, 1), (2, 2, 2, 2), (3, 3, 2, 3), (4, 2, 1, 3), (5, 3, 1, 2), (6, 3, 3, 4), (7, 2, 2, 4), (8, 2, 1, 5), (9, 3, 3, 5), (10, 10, 4, 6), (11, 10, 5, 6), (12, 3, 2, 6)]
_BLOCKS = f"blocks AS (SELECT CAST(w AS INTEGER) AS worker, (w - 1) * (SELECT count(*) FROM lineitem) // {N} AS before, w * (SELECT count(*) FROM lineitem) // {N} - (w - 1) * (SELECT count(*) FROM lineitem) // {N} AS rows FROM range(1, {N + 1}) AS r(w))"
_REPLAY = f"""{_BLOCKS}, script(seq, p, k, version) AS (VALUES {', '.join(map(str, ARRIVALS))}),
arrivals AS (SELECT seq, worker, before + (k - 1) * rows // p + 1 AS lo, before + k * rows // p AS hi, version FROM blocks, script),
replay AS (
  SELECT 0 AS seq, worker, CAST([] AS STRUCT(lo BIGINT, hi BIGINT, version INTEGER)[]) AS cache, '' AS action, 0 AS n_evicted FROM blocks
  UNION ALL
  SELECT seq, worker, CASE WHEN bad THEN cache ELSE list_append(list_filter(cache, lambda c: c.hi < lo OR c.lo > hi), CAST({{'lo': lo, 'hi': hi, 'version': version}} AS STRUCT(lo BIGINT, hi BIGINT, version INTEGER))) END,
         CASE WHEN bad THEN 'reject' WHEN hits = 0 THEN 'insert' ELSE 'replace' END, CASE WHEN bad THEN 0 ELSE hits END
  FROM (SELECT a.seq, a.worker, a.lo, a.hi, a.version, cache, len(list_filter(cache, lambda c: c.hi >= a.lo AND c.lo <= a.hi)) AS hits,
               len(list_filter(cache, lambda c: c.hi >= a.lo AND c.lo <= a.hi AND c.version >= a.version)) > 0 AS bad
        FROM replay JOIN arrivals a ON a.worker = replay.worker AND a.seq = replay.seq + 1)),
done AS (SELECT seq, worker, action, n_evicted, list_sum(list_transform(cache, lambda c: c.hi - c.lo + 1)) AS rows_covered FROM replay WHERE seq > 0)"""


def replayed(spark, d) -> DataFrame:
    blocks = layout(spark, d)
    script = spark.createDataFrame(ARRIVALS, "seq int, p int, k int, version int")
    lo, hi = P.sub_bounds_col(F.col("rows"), F.col("p"), F.col("k"))
    arrivals = blocks.crossJoin(F.broadcast(script)).select("seq", "worker", (F.col("first_row") - 1 + lo).alias("lo"), (F.col("first_row") - 1 + hi).alias("hi"), "version")

    def step(pdf: pd.DataFrame) -> pd.DataFrame:
        cache, out = IntervalCache(), []
        for x in pdf.sort_values("seq").itertuples():
            e = cache.offer(x.lo, x.hi, x.version)
            out.append((x.seq, x.worker, e.action, len(e.evicted), e.rows_covered))
        return pd.DataFrame(out, columns=["seq", "worker", "action", "n_evicted", "rows_covered"])

    return arrivals.groupBy("worker").applyInPandas(step, "seq int, worker int, action string, n_evicted int, rows_covered long")


@query(f"WITH RECURSIVE {_REPLAY} SELECT CAST(seq AS INTEGER) AS seq, worker, action, CAST(n_evicted AS INTEGER) AS n_evicted, CAST(rows_covered AS BIGINT) AS rows_covered FROM done")
def cache_replay(spark, d):
    """One cache shard a worker over scripted arrivals at changing piece counts."""
    return replayed(spark, d)


@query(f"WITH RECURSIVE {_REPLAY} SELECT CAST(seq AS INTEGER) AS seq, round(sum(rows_covered) / (SELECT sum(rows) FROM blocks), 9) AS coverage FROM done GROUP BY seq")
def coverage(spark, d):
    n = load(spark, d, "lineitem").count()
    return replayed(spark, d).groupBy("seq").agg(F.round(F.sum("rows_covered") / n, 9).alias("coverage"))


@query(f"WITH RECURSIVE {_REPLAY} SELECT worker, action, count(*) AS n, CAST(sum(n_evicted) AS BIGINT) AS evicted FROM done GROUP BY worker, action")
def evictions(spark, d):
    return replayed(spark, d).groupBy("worker", "action").agg(F.count(F.lit(1)).alias("n"), F.sum("n_evicted").alias("evicted"))


# --- load balancing -----------------------------------------------------------------------

_RAMP = f"""{TRACE}, {STATS}, ramped AS (SELECT worker, e_comm, v_comm, e_comp * (1 + 0.4 * worker / {N}) AS e_comp, v_comp * pow(1 + 0.4 * worker / {N}, 2) AS v_comp FROM stats)"""
_EQ = f"{_RAMP}, s AS (SELECT max(e_comm + e_comp) AS slowest FROM ramped), eq AS (SELECT worker, e_comm, e_comp, v_comp, greatest(1, floor(e_comp * 100 / (slowest - e_comm) + 1e-9)) AS p_new FROM ramped, s)"


def ramped(spark, d) -> DataFrame:
    return L.slow_ramp(L.worker_stats(trace(spark, d)), N)


def equalized(spark, d) -> DataFrame:
    stats = ramped(spark, d)
    slowest = stats.agg(F.max(F.col("e_comm") + F.col("e_comp")).alias("slowest"))
    count = F.greatest(F.lit(1.0), F.floor(F.col("e_comp") * 100 / (F.col("slowest") - F.col("e_comm")) + 1e-9).cast("double"))
    return stats.crossJoin(F.broadcast(slowest)).withColumn("p_new", count)


@query(f"WITH {_EQ} SELECT worker, CAST(p_new AS INTEGER) AS p_new FROM eq")
def equalize_phase(spark, d):
    return equalized(spark, d).select("worker", F.col("p_new").cast("int").alias("p_new"))


@query(f"WITH {_EQ} SELECT worker, round(e_comp * 100 / p_new, 6) AS e_comp, round(v_comp * (100 / p_new) * (100 / p_new), 6) AS v_quadratic, round(v_comp * (100 / p_new), 6) AS v_linear FROM eq")
def rescaled_stats(spark, d):
    ratio = 100 / F.col("p_new")
    return equalized(spark, d).select("worker", F.round(F.col("e_comp") * ratio, 6).alias("e_comp"), F.round(F.col("v_comp") * ratio * ratio, 6).alias("v_quadratic"), F.round(F.col("v_comp") * ratio, 6).alias("v_linear"))


@query(f"WITH {_RAMP} SELECT round(max(e_comm + e_comp) / min(e_comm + e_comp), 6) AS ratio FROM ramped")
def imbalance(spark, d):
    total = F.col("e_comm") + F.col("e_comp")
    return ramped(spark, d).agg(F.round(F.max(total) / F.min(total), 6).alias("ratio"))


@query(f"""WITH {_EQ}, r AS (SELECT max(e_comm + e_comp) / min(e_comm + e_comp) AS a, max(e_comm + e_comp * 100 / p_new) / min(e_comm + e_comp * 100 / p_new) AS b FROM eq)
SELECT round(a, 6) AS ratio_old, round(b, 6) AS ratio_new, a / b >= 1.1 AS distributed FROM r""")
def gate(spark, d):
    old, new = F.col("e_comm") + F.col("e_comp"), F.col("e_comm") + F.col("e_comp") * 100 / F.col("p_new")
    r = equalized(spark, d).agg((F.max(old) / F.min(old)).alias("a"), (F.max(new) / F.min(new)).alias("b"))
    return r.select(F.round("a", 6).alias("ratio_old"), F.round("b", 6).alias("ratio_new"), (F.col("a") / F.col("b") >= 1.1).alias("distributed"))


@query(f"""WITH RECURSIVE {TRACE}, {_sim_sql(W)}, {_BLOCKS}, u AS (SELECT i AS worker, avg(CASE WHEN done[i] <= e THEN 1.0 ELSE 0.0 END) AS u FROM sim, range(1, {N + 1}) AS r(i) WHERE t > 0 GROUP BY i)
SELECT blocks.worker, round(u * rows / (10 * (SELECT sum(rows) FROM blocks)), 9) AS h FROM blocks JOIN u ON u.worker = blocks.worker""")
def contribution(spark, d):
    """Share of all rows that each worker refreshes in an iteration, at ten pieces."""
    u = fresh_of(spark, d)
    sizes = layout(spark, d)
    total = sizes.agg(F.sum("rows").alias("n"))
    return sizes.join(F.broadcast(u), "worker").crossJoin(F.broadcast(total)).select("worker", F.round(F.col("u") * F.col("rows") / (10 * F.col("n")), 9).alias("h"))


RATES = [(1, 2), (3, 4), (7, 8), (45, 49)]
_CODED = f"""{TRACE}, rates(num, den) AS (VALUES {', '.join(map(str, RATES))}),
o AS (SELECT num, den, t, comm_ms + 10 * comp_ms * den / num AS ms, row_number() OVER (PARTITION BY num, den, t ORDER BY comm_ms + 10 * comp_ms * den / num, worker) AS w FROM trace, rates WHERE t IN (SELECT t FROM trace GROUP BY t HAVING count(*) = {N})),
c AS (SELECT num, den, t, ms FROM o WHERE w = (num * {N} + den - 1) // den)"""


def coded(spark, d) -> DataFrame:
    from pyspark.sql import Window

    rates = spark.createDataFrame(RATES, "num int, den int")
    cost = F.col("comm_ms") + 10 * F.col("comp_ms") * F.col("den") / F.col("num")
    recordings = trace(spark, d).join(whole(spark, d).select("t"), "t")  # iterations that every worker has
    rows = recordings.crossJoin(F.broadcast(rates)).withColumn("ms", cost)
    rank = F.row_number().over(Window.partitionBy("num", "den", "t").orderBy("ms", "worker"))
    return rows.withColumn("w", rank).where(F.col("w") == F.ceil(F.col("num") * N / F.col("den"))).select("num", "den", "t", "ms")


@query(f"WITH {_CODED} SELECT t, round(ms, 6) AS ms FROM c WHERE num = 45")
def coded_latency(spark, d):
    """Latency of ideal coding at rate 45/49: the ceil(rN)-th of the enlarged tasks."""
    return coded(spark, d).where("num = 45").select("t", *r6("ms"))


@query(f"WITH {_CODED} SELECT round(num / den, 6) AS rate, round(sum(ms), 3) AS total_ms FROM c GROUP BY num, den")
def coded_sweep(spark, d):
    return coded(spark, d).groupBy("num", "den").agg(F.round(F.sum("ms"), 3).alias("total_ms")).select(F.round(F.col("num") / F.col("den"), 6).alias("rate"), "total_ms")


# --- balanced and compared runs (beyond SQL; held against NumPy loops and known orderings in the tests) ----


def _registered(name: str, f):
    f.__name__ = name
    QUERIES[name] = f


for _m in ("stale_cache", "avg_gradient", "sgd"):
    _registered(f"run_{_m}_balanced_logistic", lambda spark, d, m=_m: workloads.sweep(spark, d, "logistic", [(m, 3, True)], seeds=1))
_registered("run_coded_bound", lambda spark, d: workloads.coded_run(spark, d, 45, 49))
_registered("rebalance_counts", lambda spark, d: workloads.rebalanced(spark, d))
_registered("balancer_script", lambda spark, d: workloads.scripted_balancing(spark, d))
_registered("order_stats_models", lambda spark, d: workloads.order_stat_models(spark, d))
_registered("method_comparison_logistic", lambda spark, d: workloads.comparison(spark, d, "logistic", 8, 3, iterations=150))
_registered("method_comparison_pca", lambda spark, d: workloads.comparison(spark, d, "pca", 8, 3, iterations=150))
_registered("option_ablations", lambda spark, d: workloads.ablations(spark, d))
_registered("delivery_and_cache", lambda spark, d: workloads.delivery_rows(spark, d))
for _m in ("stale_cache", "avg_gradient", "sgd"):
    _registered(f"run_{_m}_balanced_pca", lambda spark, d, m=_m: workloads.sweep(spark, d, "pca", [(m, 3, True)], seeds=1))
_registered("release_comparison", lambda spark, d: workloads.release_comparison(spark, d))
_registered("cloud_comparison", lambda spark, d: workloads.cloud_comparison(spark, d, iterations=250, seeds=2))
_registered("balancing_ablations", lambda spark, d: workloads.balancing_ablations(spark, d))
