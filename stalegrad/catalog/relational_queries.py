"""Relational forms the methods rest on: joins of each kind, grouping sets, windows, maps, JSON, subqueries, aggregates of vectors."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from stalegrad.catalog import latency_queries as Q
from stalegrad.catalog.latency_queries import N, STATS, TRACE, layout, trace
from stalegrad.functions.aggregates import gram_sum, interval_rows, vector_sum
from stalegrad.operators import latency as L
from stalegrad.operators import matrix as M
from stalegrad.operators import order_stats as O
from stalegrad.operators import partitioning as P
from stalegrad.operators import simulate
from stalegrad.plans.balancer import blend
from stalegrad.sources.tables import load

QUERIES, ORACLES = {}, {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


# --- joins ---------------------------------------------------------------------------------

_ORDERS = "SELECT o_orderstatus, count(*) AS rows, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderstatus"


def _orders(spark, d, hint: str):
    joined = load(spark, d, "lineitem").select("l_orderkey", "l_quantity").join(load(spark, d, "orders").select("o_orderkey", "o_orderstatus").hint(hint), F.col("l_orderkey") == F.col("o_orderkey"))
    return joined.groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("rows"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query(_ORDERS)
def order_rows_merge(spark, d):
    """Both sides large: shuffled, sorted and merged."""
    return _orders(spark, d, "merge")


@query(_ORDERS)
def order_rows_shuffle_hash(spark, d):
    """One side of medium size: shuffled, hashed within the partition."""
    return _orders(spark, d, "shuffle_hash")


@query(f"""WITH {Q._PIECES}, a AS (SELECT worker, k, lo FROM pieces WHERE parts = 2), b AS (SELECT worker, k, lo FROM pieces WHERE parts = 3)
SELECT coalesce(a.worker, b.worker) AS worker, coalesce(a.k, b.k) AS k, a.lo AS lo_before, b.lo AS lo_after FROM a FULL JOIN b ON a.worker = b.worker AND a.k = b.k""")
def layout_change(spark, d):
    """Pieces before and after a re-partitioning side by side; a piece that only one layout has keeps a null."""
    base = layout(spark, d)
    a, b = (P.pieces(base, p).select("worker", "k", F.col("lo").alias(name)) for p, name in ((2, "lo_before"), (3, "lo_after")))
    return a.join(b, ["worker", "k"], "full").select("worker", "k", "lo_before", "lo_after")


# --- grouping, windows, structures -----------------------------------------------------------

_KIND = f"{TRACE}, kinds AS (SELECT trace.worker, event_type, comp_ms FROM trace JOIN events USING (event_id))"


def _kinds(spark, d):
    return trace(spark, d).join(load(spark, d, "events").select("event_id", "event_type"), "event_id").select("worker", "event_type", "comp_ms")


@query(f"WITH {_KIND} SELECT worker, event_type, count(*) AS n, round(avg(comp_ms), 6) AS mean_ms FROM kinds GROUP BY CUBE (worker, event_type)")
def latency_cube(spark, d):
    return _kinds(spark, d).cube("worker", "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("comp_ms"), 6).alias("mean_ms"))


@query(f"WITH {_KIND} SELECT worker, event_type, count(*) AS n FROM kinds GROUP BY GROUPING SETS ((worker), (event_type), ())")
def latency_grouping_sets(spark, d):
    _kinds(spark, d).createOrReplaceTempView("latency_kinds")
    return spark.sql("SELECT worker, event_type, count(*) AS n FROM latency_kinds GROUP BY GROUPING SETS ((worker), (event_type), ())")


@query(f"WITH {TRACE} SELECT CAST((t - 1) // 100 AS INTEGER) AS block, {', '.join(f'round(avg(comp_ms) FILTER (WHERE worker = {i}), 6) AS w{i}' for i in range(1, N + 1))} FROM trace GROUP BY 1")
def latency_pivot(spark, d):
    blocks = trace(spark, d).select(F.floor((F.col("t") - 1) / 100).cast("int").alias("block"), F.concat(F.lit("w"), "worker").alias("name"), "comp_ms")
    return blocks.groupBy("block").pivot("name", [f"w{i}" for i in range(1, N + 1)]).agg(F.round(F.avg("comp_ms"), 6))


_W = "(PARTITION BY worker ORDER BY round_trip_ms, event_id)"


@query(f"""WITH {TRACE} SELECT worker, event_id, CAST(ntile(4) OVER {_W} AS INTEGER) AS quarter, round(percent_rank() OVER {_W}, 9) AS pr,
round(lead(round_trip_ms) OVER (PARTITION BY worker ORDER BY t) - round_trip_ms, 6) AS next_change FROM trace""")
def latency_ranks(spark, d):
    w, by_t = Window.partitionBy("worker").orderBy("round_trip_ms", "event_id"), Window.partitionBy("worker").orderBy("t")
    change = F.lead("round_trip_ms").over(by_t) - F.col("round_trip_ms")
    return trace(spark, d).select("worker", "event_id", F.ntile(4).over(w).alias("quarter"), F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(change, 6).alias("next_change"))


@query(f"""WITH {TRACE}, f AS (SELECT t FROM trace GROUP BY t HAVING count(*) = {N}), r AS (SELECT t, round_trip_ms, row_number() OVER (PARTITION BY t ORDER BY round_trip_ms, worker) AS n FROM trace WHERE t IN (SELECT t FROM f))
SELECT t, round(round_trip_ms, 6) AS third_ms FROM r WHERE n = 3""")
def quorum_times(spark, d):
    """The third fastest latency of each iteration that all workers have."""
    w = Window.partitionBy("t").orderBy("round_trip_ms", "worker").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    tr = trace(spark, d).withColumn("third", F.nth_value("round_trip_ms", 3).over(w))
    return tr.groupBy("t").agg(F.count(F.lit(1)).alias("n"), F.first("third").alias("third")).where(F.col("n") == N).select("t", F.round("third", 6).alias("third_ms"))


@query(f"WITH {Q.BLOCKS} SELECT worker, CAST(CASE WHEN worker <= 4 THEN 10 ELSE 12 END AS INTEGER) AS parts, (last_row - first_row + 1) // (CASE WHEN worker <= 4 THEN 10 ELSE 12 END) AS least_rows FROM blocks")
def count_vector(spark, d):
    """Piece counts by worker as one map, looked up on each block."""
    pairs = spark.range(1, N + 1).select(F.struct(F.col("id").cast("int").alias("key"), F.when(F.col("id") <= 4, 10).otherwise(12).alias("value")).alias("e"))
    counts = pairs.agg(F.map_from_entries(F.collect_list("e")).alias("counts"))
    parts = F.element_at("counts", F.col("worker"))
    return layout(spark, d).crossJoin(F.broadcast(counts)).select("worker", parts.alias("parts"), F.floor(F.col("rows") / parts).cast("long").alias("least_rows"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, CAST(json_extract_string(props, '$.k') AS INTEGER) + 1 AS next_k FROM events")
def event_props(spark, d):
    """The properties as a struct, and a changed struct written as JSON and read again."""
    parsed = load(spark, d, "events").select("event_id", F.from_json("props", "k int").alias("p"))
    again = F.from_json(F.to_json(F.struct((F.col("p.k") + 1).alias("k"))), "k int")
    return parsed.select("event_id", F.col("p.k").alias("k"), again["k"].alias("next_k"))


@query(f"""WITH {TRACE} SELECT worker, count(*) AS n FROM trace a WHERE comp_ms > (SELECT avg(comp_ms) FROM trace b WHERE b.worker = a.worker)
AND EXISTS (SELECT 1 FROM trace c WHERE c.worker = a.worker AND c.comm_ms < 0.2) AND comm_ms > (SELECT avg(comm_ms) FROM trace) GROUP BY worker""")
def slow_recordings(spark, d):
    """Scalar, correlated and exists subqueries in Spark SQL, decorrelated by the optimiser."""
    trace(spark, d).createOrReplaceTempView("recordings")
    return spark.sql("""SELECT worker, count(*) AS n FROM recordings a WHERE comp_ms > (SELECT avg(comp_ms) FROM recordings b WHERE b.worker = a.worker)
      AND EXISTS (SELECT 1 FROM recordings c WHERE c.worker = a.worker AND c.comm_ms < 0.2) AND comm_ms > (SELECT avg(comm_ms) FROM recordings) GROUP BY worker""")


@query("SELECT count(DISTINCT user_id) AS users, true AS near FROM events")
def distinct_users(spark, d):
    """Exact distinct count, and whether the sketch is within a twentieth of it."""
    both = load(spark, d, "events").agg(F.countDistinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.01).alias("about"))
    return both.select("users", (F.abs(F.col("about") - F.col("users")) <= F.col("users") * 0.05).alias("near"))


# --- vectors, loads ------------------------------------------------------------------------------

@query("SELECT label, CAST(i AS INTEGER) AS i, round(sum(CAST(embedding[i] AS DOUBLE)), 6) AS total FROM embeddings, range(1, 65) AS r(i) GROUP BY label, i")
def vector_sums(spark, d):
    """Sums of the embeddings of each label by the vector aggregate."""
    sums = load(spark, d, "embeddings").select("label", F.col("embedding").cast("array<double>").alias("v")).groupBy("label").agg(vector_sum("v").alias("s"))
    return sums.select("label", F.posexplode("s").alias("i", "x")).select("label", (F.col("i") + 1).alias("i"), F.round("x", 6).alias("total"))


@query("""SELECT CAST(a AS INTEGER) AS a, CAST(b AS INTEGER) AS b, round(sum(CAST(embedding[a] AS DOUBLE) * CAST(embedding[b] AS DOUBLE)), 6) AS val
FROM embeddings, range(1, 9) AS x(a), range(1, 9) AS y(b) GROUP BY 1, 2""")
def gram_sums(spark, d):
    """Gram matrix of the first eight embedding columns: by salt first, so no task holds all vectors."""
    parts = load(spark, d, "embeddings").select(F.pmod("vec_id", F.lit(16)).alias("salt"), F.slice("embedding", 1, 8).cast("array<double>").alias("v"))
    total = parts.groupBy("salt").agg(gram_sum("v").alias("g")).agg(vector_sum("g").alias("g"))
    return total.select(F.posexplode("g").alias("at", "x")).select((F.floor(F.col("at") / 8) + 1).cast("int").alias("a"), (F.col("at") % 8 + 1).alias("b"), F.round("x", 6).alias("val"))


@query(f"""WITH {Q._PIECES}, t AS (SELECT worker, lo, hi FROM pieces WHERE (parts = 2 AND k = 1) OR (parts = 3 AND k = 2)) SELECT worker, max(hi) - min(lo) + 1 AS rows FROM t GROUP BY worker""")
def union_rows(spark, d):
    """Rows in the union of overlapping pieces of two layouts."""
    base = layout(spark, d)
    both = P.pieces(base, 2).where("k = 1").unionByName(P.pieces(base, 3).where("k = 2"))
    return both.groupBy("worker").agg(interval_rows("lo", "hi").alias("rows"))


@query("SELECT vec_id, CAST(len(embedding) + 1 AS INTEGER) AS width, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE))) + 1.0, 6) AS total FROM embeddings")
def intercept_rows(spark, d):
    """The embeddings with an intercept column of ones behind them."""
    rows = M.add_intercept(load(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("features")))
    return rows.select("vec_id", F.size("features").alias("width"), F.round(F.aggregate("features", F.lit(0.0), lambda a, x: a + x), 6).alias("total"))


@query(f"""WITH {Q.BLOCKS} SELECT worker, CAST(2 * 7 * (last_row - first_row + 1) AS DOUBLE) AS operations, CAST(28 AS INTEGER) AS bytes,
round(2.0 * 7 * (last_row - first_row + 1) * 49 / 45, 6) AS coded_operations FROM blocks""")
def task_costs(spark, d):
    """Operations of a whole block, bytes of an iterate, and the load under coding at 45/49."""
    per_row = M.comp_load(1, 7, 1)
    ops = F.col("rows") * per_row
    return layout(spark, d).select("worker", ops.alias("operations"), F.lit(M.comm_bytes(7, 1)).alias("bytes"), F.round(ops * M.coded_load(1.0, 45, 49), 6).alias("coded_operations"))


# --- predictions and profiles ----------------------------------------------------------------------

_SEEN = f"seen AS (SELECT w, avg(round_trip_ms) AS o FROM (SELECT row_number() OVER (PARTITION BY t ORDER BY round_trip_ms, worker) AS w, round_trip_ms FROM trace WHERE t IN (SELECT t FROM trace GROUP BY t HAVING count(*) = {N})) GROUP BY w)"
_MC = Q.ORACLES["order_stats_mc"]


@query(f"SELECT CAST(p.w AS INTEGER) AS w, round(abs(p.mean_ms - s.o), 5) AS abs_error, round(abs(p.mean_ms - s.o) / s.o, 8) AS rel_error FROM ({_MC}) p JOIN (WITH {TRACE}, {_SEEN} SELECT * FROM seen) s ON s.w = p.w")
def prediction_error(spark, d):
    """Predicted against recorded order statistics."""
    tr = trace(spark, d)
    predicted = O.hashed_order_stats(L.shifted_exp_moments(L.worker_stats(tr)), 200, 5).select("w", F.round("mean_ms", 6).alias("mean_ms"))
    return simulate.prediction_error(predicted, O.empirical_order_stats(tr, N), "w", "mean_ms").select("w", F.round("abs_error", 5).alias("abs_error"), F.round("rel_error", 8).alias("rel_error"))


@query(f"""WITH {TRACE}, b AS (SELECT worker, CASE WHEN t % 3 = 0 THEN 10 ELSE 20 END AS parts, comp_ms / (CASE WHEN t % 3 = 0 THEN 1 ELSE 2 END) AS c FROM trace),
s AS (SELECT worker, parts, count(*) AS n, avg(c) AS e, var_samp(c) AS v FROM b GROUP BY worker, parts)
SELECT worker, round(sum(n * e * parts / 25.0) / sum(n), 6) AS e_comp, round(sum(n * v * (parts / 25.0) * (parts / 25.0)) / sum(n), 4) AS v_comp FROM s GROUP BY worker""")
def blended_stats(spark, d):
    """Moments at 25 pieces from recordings at 10 and 20, weighted by observations."""
    parts = F.when(F.col("t") % 3 == 0, 10).otherwise(20)
    seen = trace(spark, d).select("worker", parts.alias("parts"), (F.col("comp_ms") * 10 / parts).alias("c"))
    stats = seen.groupBy("worker", "parts").agg(F.count(F.lit(1)).alias("n_obs"), F.avg("c").alias("e_comp"), F.var_samp("c").alias("v_comp"))

    def one(key, pdf):
        import pandas as pd

        return pd.DataFrame([(key[0], *blend(pdf, 25))], columns=["worker", "e_comp", "v_comp"])

    return stats.groupBy("worker").applyInPandas(one, "worker int, e_comp double, v_comp double").select("worker", F.round("e_comp", 6).alias("e_comp"), F.round("v_comp", 4).alias("v_comp"))


@query(f"""WITH {TRACE.replace(f'% {N}', '% 72')}, f AS (SELECT t FROM trace GROUP BY t HAVING count(*) = 72),
r AS (SELECT row_number() OVER (PARTITION BY t ORDER BY ms, worker) AS w, ms FROM (SELECT t, worker, comm_ms + (1000.0 + comp_ms - 1000.0) * (1 + 0.4 * worker / 72) AS ms FROM trace WHERE t IN (SELECT t FROM f)))
SELECT CAST(w AS INTEGER) AS w, round(avg(ms), 6) AS mean_ms FROM r GROUP BY w""")
def order_stats_72(spark, d):
    """Order statistics of 72 workers under the ramp."""
    return O.empirical_order_stats(trace(spark, d, 72, 0.4), 72).select("w", F.round("mean_ms", 6).alias("mean_ms"))


@query(f"""WITH {TRACE}, two AS (SELECT worker, t, round_trip_ms FROM trace WHERE worker <= 2), first AS (SELECT * FROM two WHERE t <= 100)
SELECT worker, t, round(round_trip_ms, 6) AS latency, round(cume_dist() OVER (PARTITION BY worker ORDER BY round_trip_ms), 6) AS cdf FROM first""")
def two_worker_series(spark, d):
    """Two workers over a hundred iterations, the window that the experiment itself names, with their empirical CDF."""
    first = trace(spark, d).where("worker <= 2 AND t <= 100")
    return first.select("worker", "t", F.round("round_trip_ms", 6).alias("latency"), F.round(F.cume_dist().over(Window.partitionBy("worker").orderBy("round_trip_ms")), 6).alias("cdf"))
