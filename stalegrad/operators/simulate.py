"""Event-driven simulation of a coordinator that waits for w fresh results.

A worker runs one task at a time and keeps only the newest waiting one.  In an
iteration that starts at s a worker free at f begins at max(s, f); the iteration
ends once w results of this iteration are in, plus a margin of the time waited.
A task begun before the end runs on and arrives late; one not begun is replaced.
As a worker begins at most one task an iteration, a recurrence over the free
times gives the same as an event queue (``engine='heap'`` is that queue).
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stalegrad.functions.draws import gamma_draws
from stalegrad.sources.tables import replicates


@dataclass
class Schedule:
    """Iteration ends, freshness, and every task that was begun, in order of arrival."""

    ends: np.ndarray
    fresh: np.ndarray
    tasks: list[tuple[float, int, int, float]] = field(default_factory=list)  # (finish, worker, version, start)


def step_end(start: float, quorum: float, margin: float) -> float:
    return max(quorum, start + (1 + margin) * (quorum - start))


def recurrence(latency: np.ndarray, w: int, margin: float = 0.0, keep_tasks: bool = False) -> Schedule:
    """``latency[t, i]``: what worker i's task of iteration t takes."""
    length, n = latency.shape
    free, now = np.zeros(n), 0.0
    ends, fresh, tasks = np.empty(length), np.zeros((length, n), dtype=bool), []
    for t in range(length):
        begin = np.maximum(now, free)
        done = begin + latency[t]
        end = step_end(now, np.partition(done, w - 1)[w - 1], margin)
        begun = begin < end
        fresh[t] = done <= end
        if keep_tasks:
            tasks += [(float(done[i]), int(i), t, float(begin[i])) for i in np.flatnonzero(begun | fresh[t])]
        free = np.where(begun | fresh[t], done, free)
        ends[t] = now = end
    tasks.sort()
    return Schedule(ends, fresh, tasks)


def stream(latencies: DataFrame, w: int, margin: float = 0.0) -> DataFrame:
    """``recurrence`` over rows (t, x array by worker) of any number, in one ordered pass.

    Each iteration needs the one before, so a single task walks along t; it keeps
    the free times and the running tasks only.  Gives (t, end_ms, blind_ms, fresh,
    staleness of the results that arrived in t); ``blind_ms`` sums the one-shot
    order statistics.
    """

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        free, now, blind, step, running = None, 0.0, 0.0, 0, []
        for batch in batches:
            out = []
            for t, x in zip(batch["t"], batch["x"], strict=True):
                x = np.asarray(x)
                free = np.zeros(len(x)) if free is None else free
                begin = np.maximum(now, free)
                done = begin + x
                end = step_end(now, np.partition(done, w - 1)[w - 1], margin)
                hit = done <= end
                kept = (begin < end) | hit
                running += [(finish, step) for finish in done[kept].tolist()]
                came = [step - version for finish, version in running if finish <= end]
                running = [task for task in running if task[0] > end]
                free = np.where(kept, done, free)
                blind += float(np.partition(x, w - 1)[w - 1])
                now, step = float(end), step + 1
                out.append((t, now, blind, hit.tolist(), came))
            yield pd.DataFrame(out, columns=["t", "end_ms", "blind_ms", "fresh", "staleness"])

    ordered = latencies.select("t", "x").repartition(1).sortWithinPartitions("t")
    return ordered.mapInPandas(run, "t int, end_ms double, blind_ms double, fresh array<boolean>, staleness array<int>")


def heap(latency: np.ndarray, w: int, margin: float = 0.0) -> Schedule:
    """The same by an explicit event queue."""
    length, n = latency.shape
    busy_until, queue = [0.0] * n, []
    running: list[int | None] = [None] * n
    waiting: list[int | None] = [None] * n
    ends, fresh = np.empty(length), np.zeros((length, n), dtype=bool)
    now = 0.0
    for t in range(length):
        for i in range(n):
            if running[i] is None:
                running[i], busy_until[i] = t, now + latency[t, i]
                heapq.heappush(queue, (busy_until[i], i))
            else:
                waiting[i] = t
        got, start, end = 0, now, float("inf")
        while queue and queue[0][0] <= end:
            at, i = heapq.heappop(queue)
            if running[i] == t:
                fresh[t, i] = True
                got += 1
                if got == w:
                    end = step_end(start, at, margin)
            running[i] = None
            if waiting[i] is not None and at < end:
                running[i], waiting[i] = waiting[i], None
                heapq.heappush(queue, (at + latency[running[i], i], i))
        waiting = [None] * n
        ends[t] = now = end
    return Schedule(ends, fresh)


def draws(stats: pd.DataFrame, length: int, rng: np.random.Generator) -> np.ndarray:
    """Latencies (iteration, worker) from the two gammas of each worker."""
    n = len(stats)
    comm = gamma_draws(rng, stats["e_comm"].to_numpy(), stats["v_comm"].fillna(0).to_numpy(), (length, n))
    comp = gamma_draws(rng, stats["e_comp"].to_numpy(), stats["v_comp"].fillna(0).to_numpy(), (length, n))
    return comm + comp


def simulate(spark: SparkSession, stats: DataFrame, w: int, length: int, count: int, margin: float = 0.0, seed: int = 0) -> DataFrame:
    """(replicate, t, end_ms, fresh array<boolean>): replicates spread over tasks, each seeded by its number.

    ``stats`` has one row a worker, so it is collected and travels with the tasks.
    """
    table = stats.orderBy("worker").toPandas()

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for r in batch["replicate"]:
                s = recurrence(draws(table, length, np.random.default_rng([seed, int(r)])), w, margin)
                yield pd.DataFrame({"replicate": r, "t": np.arange(1, length + 1, dtype=np.int32), "end_ms": s.ends, "fresh": list(s.fresh)})

    return replicates(spark, count).mapInPandas(run, "replicate long, t int, end_ms double, fresh array<boolean>")


def cumulative_latency(sim: DataFrame) -> DataFrame:
    """Mean end of each iteration over the replicates."""
    return sim.groupBy("t").agg(F.avg("end_ms").alias("cum_ms"))


def fresh_fraction(sim: DataFrame) -> DataFrame:
    flat = sim.select(F.posexplode("fresh").alias("i", "hit"))
    return flat.groupBy((F.col("i") + 1).alias("worker")).agg(F.avg(F.col("hit").cast("double")).alias("u"))


def predict_independent_iterations(mean_ms: float, length: int) -> np.ndarray:
    """The prediction that forgets busy workers: t times the one-shot order statistic."""
    return mean_ms * np.arange(1, length + 1)


def prediction_error(predicted: DataFrame, observed: DataFrame, key: str, value: str) -> DataFrame:
    """Absolute and relative error of two curves at the same places."""
    both = predicted.select(key, F.col(value).alias("_p")).join(observed.select(key, F.col(value).alias("_o")), key)
    return both.select(key, F.abs(F.col("_p") - F.col("_o")).alias("abs_error"), (F.abs(F.col("_p") - F.col("_o")) / F.col("_o")).alias("rel_error"))
