"""Streaming forms: windowed profiles, burst sessions, round-trip matching and the keyed cache.

Watermarks drop recordings that come too late for a profile.  Whether a
*subgradient* is still wanted is never a question of time but of versions, so
the cache stream has no watermark.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from stalegrad.operators.cache import Entry, IntervalCache


def windowed_profile(trace: DataFrame, window: str = "10 seconds", slide: str | None = None, late: str = "10 seconds") -> DataFrame:
    """Moments by worker over tumbling (or sliding) event-time windows."""
    spans = F.window("ts", window, slide) if slide else F.window("ts", window)
    return trace.withWatermark("ts", late).groupBy(spans.alias("span"), "worker").agg(
        F.count(F.lit(1)).alias("n_obs"), F.avg("comm_ms").alias("e_comm"), F.var_samp("comm_ms").alias("v_comm"), F.avg("comp_ms").alias("e_comp"), F.var_samp("comp_ms").alias("v_comp")
    )


def burst_sessions(trace: DataFrame, threshold_ms: float, gap: str = "1 minute", late: str = "1 minute") -> DataFrame:
    """Sessions of slow recordings of a worker."""
    slow = trace.where(F.col("comp_ms") > threshold_ms).withWatermark("ts", late)
    return slow.groupBy(F.session_window("ts", gap).alias("span"), "worker").agg(F.count(F.lit(1)).alias("n"))


def deduplicated(trace: DataFrame, late: str = "10 seconds") -> DataFrame:
    """Replayed recordings of the same (worker, t) dropped within the watermark."""
    return trace.withWatermark("ts", late).dropDuplicatesWithinWatermark(["worker", "t"])


def match_round_trips(sent: DataFrame, replied: DataFrame, limit: str = "1 hour") -> DataFrame:
    """Send and reply records of one (worker, version): the round trip and its communication part.

    ``sent`` has (worker, version, sent_ts), ``replied`` (worker, version, reply_ts, comp_ms).
    """
    left = sent.withWatermark("sent_ts", limit).alias("s")
    right = replied.withWatermark("reply_ts", limit).alias("r")
    same = (F.col("s.worker") == F.col("r.worker")) & (F.col("s.version") == F.col("r.version"))
    near = (F.col("r.reply_ts") >= F.col("s.sent_ts")) & (F.col("r.reply_ts") <= F.col("s.sent_ts") + F.expr(f"INTERVAL {limit}"))
    trip = (F.unix_micros("r.reply_ts") - F.unix_micros("s.sent_ts")) / 1000.0
    return left.join(right, same & near).select("s.worker", "s.version", F.col("r.reply_ts").alias("ts"), trip.alias("round_trip_ms"), (trip - F.col("r.comp_ms")).alias("comm_ms"), "r.comp_ms")


def exact_moving_profile(trace: DataFrame, window_ms: int = 10_000) -> DataFrame:
    """Moments over (ts - window, ts] after each micro-batch, one row a worker and batch."""

    def step(key: tuple[int], batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        times, comm, comp = (list(x) for x in state.get) if state.exists else ([], [], [])
        for b in batches:
            times += (b["ts"].astype("int64") // 10 ** (3 if str(b["ts"].dtype).endswith("[ns]") or "ns" in str(b["ts"].dtype) else 0)).tolist()
            comm += b["comm_ms"].tolist()
            comp += b["comp_ms"].tolist()
        last = max(times)
        kept = sorted((t, a, c) for t, a, c in zip(times, comm, comp, strict=True) if t > last - window_ms * 1000)
        times, comm, comp = (list(x) for x in zip(*kept, strict=True))
        state.update((times, comm, comp))
        a, c = pd.Series(comm), pd.Series(comp)
        yield pd.DataFrame({"worker": [key[0]], "n_obs": [len(kept)], "e_comm": [a.mean()], "v_comm": [a.var()], "e_comp": [c.mean()], "v_comp": [c.var()]})

    out = "worker int, n_obs long, e_comm double, v_comm double, e_comp double, v_comp double"
    return trace.groupBy("worker").applyInPandasWithState(step, out, "times array<long>, comm array<double>, comp array<double>", "append", GroupStateTimeout.NoTimeout)


def stream_cache(arrivals: DataFrame) -> DataFrame:
    """The interval cache as keyed state: one shard a worker, as pieces never cross worker blocks.

    ``arrivals`` has (seq, worker, lo, hi, version); each gives its action and the
    rows its shard covers afterwards.
    """

    def step(key: tuple[int], batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        cache = IntervalCache()
        if state.exists:
            for lo, hi, version in zip(*state.get, strict=True):
                cache.starts.append(lo)
                cache.entries.append(Entry(lo, hi, version))
                cache.rows += hi - lo + 1
        rows = []
        for x in pd.concat(list(batches)).sort_values("seq").itertuples():
            e = cache.offer(int(x.lo), int(x.hi), int(x.version))
            rows.append((x.seq, key[0], e.action, len(e.evicted), cache.rows))
        state.update(([e.lo for e in cache.entries], [e.hi for e in cache.entries], [e.version for e in cache.entries]))
        yield pd.DataFrame(rows, columns=["seq", "worker", "action", "n_evicted", "rows_covered"])

    return arrivals.groupBy("worker").applyInPandasWithState(step, "seq long, worker int, action string, n_evicted int, rows_covered long", "lo array<long>, hi array<long>, version array<int>", "append", GroupStateTimeout.NoTimeout)


def run_once(stream: DataFrame, sink: str, checkpoint: str, mode: str = "append") -> None:
    """All that is there now into a Parquet folder, restartable from ``checkpoint``."""
    query = stream.writeStream.format("parquet").outputMode(mode).option("path", sink).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()


def step_each_batch(gradients: DataFrame, v, eta: float, n: int, checkpoint: str, on_step=None):
    """An optimiser step for every micro-batch of (lo, hi, grad array<double>) rows; returns the last iterate.

    The batch is summed on the executors (one vector and a row count reach the
    driver), scaled by the share of rows it covers, and ``on_step(batch id, iterate)``
    sees every step.
    """
    from stalegrad.functions.aggregates import vector_sum

    state = {"v": v}

    def step(batch: DataFrame, number: int) -> None:
        rows = batch.agg(F.sum(F.col("hi") - F.col("lo") + 1)).first()[0]
        if rows:
            some = batch.groupBy(F.pmod(F.xxhash64("lo"), F.lit(32)).alias("salt")).agg(vector_sum("grad").alias("g"))
            total = np.array(some.agg(vector_sum("g")).first()[0])
            state["v"] = state["v"] - eta * total.reshape(state["v"].shape) / (rows / n)
        if on_step:
            on_step(number, state["v"])

    gradients.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return state["v"]


def into_table(stream: DataFrame, name: str, mode: str, checkpoint: str) -> None:
    """All that is there now into an in-memory table, in complete, update or append mode."""
    stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
