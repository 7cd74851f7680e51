"""The method in wall-clock time: one driver thread a logical worker, one Spark job a task.

Workers take the newest iterate when they become idle; the coordinator goes on
after ``w`` results of the current version and the margin, and folds late ones
into the cache.  Round trips and kernel seconds are recorded as a trace.  Not
deterministic: for smoke runs and profiling, with speculation off.
"""

from __future__ import annotations

import queue
import threading
import time

import numpy as np
import pandas as pd
from pyspark import InheritableThread

from stalegrad.operators.cache import IntervalCache
from stalegrad.operators.partitioning import next_sub, sub_bounds


def run(kernel, objective, n: int, workers: int, w: int, iterations: int, parts: int = 10, eta: float = 0.25, margin: float = 0.02, use_late: bool = True) -> tuple[pd.DataFrame, pd.DataFrame]:
    """(trajectory, trace)."""
    news, results = threading.Condition(), queue.Queue()
    state = {"version": 0, "v": objective.start(), "stop": False}

    def worker(i: int) -> None:
        first, last = sub_bounds(n, workers, i + 1)
        rows, k, done = last - first + 1, 0, -1
        while True:
            with news:
                news.wait_for(lambda: state["stop"] or state["version"] > done)
                if state["stop"]:
                    return
                version, v, sent = state["version"], state["v"], time.time()
            k = next_sub(k, parts) if k else 1
            lo, hi = sub_bounds(rows, parts, k)
            began = time.time()
            try:
                grad = kernel.parts(objective, [(first - 1 + lo, first - 1 + hi)], v)[0]
            except Exception as e:  # the coordinator raises it
                results.put(e)
                return
            results.put((i, version, first - 1 + lo, first - 1 + hi, grad, time.time() - began, sent))
            done = version

    threads = [InheritableThread(target=worker, args=(i,)) for i in range(workers)]
    for t in threads:
        t.start()
    cache, steps, trace, began = IntervalCache(), [], [], time.time()
    try:
        for version in range(iterations):
            start, fresh, until = time.time(), 0, None
            while until is None or time.time() < until:
                try:
                    r = results.get(timeout=600 if until is None else max(0.0, until - time.time()))
                except queue.Empty:
                    if until is None:
                        raise TimeoutError("no result within ten minutes") from None
                    break
                if isinstance(r, Exception):
                    raise r
                i, made, lo, hi, grad, comp, sent = r
                trip = time.time() - sent
                trace.append((i + 1, made, trip * 1000, comp * 1000, max(0.0, trip - comp) * 1000))
                if made == version or use_late:
                    cache.offer(lo, hi, made, grad)
                fresh += made == version
                if fresh == w and until is None:
                    until = start + (1 + margin) * (time.time() - start)
            v = state["v"]
            v = objective.project(v - eta * (cache.total / cache.coverage(n) + objective.regulariser_grad(v)))
            steps.append((version + 1, (time.time() - began) * 1000, cache.coverage(n), fresh))
            with news:
                state["v"], state["version"] = v, version + 1
                news.notify_all()
    finally:
        with news:
            state["stop"] = True
            news.notify_all()
        for t in threads:
            t.join(60)
    out = pd.DataFrame(steps, columns=["t", "time_ms", "coverage", "n_fresh"])
    out["objective"] = np.nan
    out.loc[len(out) - 1, "objective"] = kernel.value(objective, state["v"])
    return out, pd.DataFrame(trace, columns=["worker", "version", "round_trip_ms", "comp_ms", "comm_ms"])
