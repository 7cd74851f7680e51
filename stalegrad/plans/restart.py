"""State of a long run in shared storage, so that a lost driver goes on where it stopped."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ROWS = "t int, kind string, lo long, hi long, version int, height int, width int, vals array<double>"


@dataclass
class RunStore:
    """Snapshots of (iterate, cache entries, subgradients under way) as one Parquet folder each ``every`` iterations.

    A folder without its success mark is a write that was cut off and is passed over.
    """

    spark: SparkSession
    path: str
    every: int = 50

    def save(self, t: int, v: np.ndarray, entries: list, waiting: dict[tuple[int, int, int], np.ndarray]) -> None:
        def row(kind: str, lo: int, hi: int, version: int, x: np.ndarray) -> tuple:
            return (t, kind, int(lo), int(hi), int(version), x.shape[0], x.shape[1], x.ravel().tolist())

        rows = [row("iterate", 0, 0, t, v), *(row("entry", e.lo, e.hi, e.version, e.grad) for e in entries), *(row("waiting", lo, hi, version, g) for (version, lo, hi), g in waiting.items())]
        self.spark.createDataFrame(rows, ROWS).write.mode("overwrite").parquet(f"{self.path}/t={t:09d}")

    def _folders(self) -> list[str]:
        context = self.spark.sparkContext
        root = context._jvm.org.apache.hadoop.fs.Path(self.path)
        fs = root.getFileSystem(context._jsc.hadoopConfiguration())
        if not fs.exists(root):
            return []
        found = [s.getPath() for s in fs.listStatus(root)]
        return sorted(p.toString() for p in found if fs.exists(context._jvm.org.apache.hadoop.fs.Path(p, "_SUCCESS")))

    def load(self) -> tuple[int, np.ndarray, list[tuple[int, int, int, np.ndarray]], dict[tuple[int, int, int], np.ndarray]] | None:
        """The newest whole snapshot: iterations done, iterate, entries (lo, hi, version, grad), waiting subgradients."""
        folders = self._folders()
        if not folders:
            return None
        rows = self.spark.read.schema(ROWS).parquet(folders[-1]).collect()
        shaped = [(r, np.array(r["vals"]).reshape(r["height"], r["width"])) for r in rows]
        first = next((r, x) for r, x in shaped if r["kind"] == "iterate")
        entries = [(r["lo"], r["hi"], r["version"], x) for r, x in shaped if r["kind"] == "entry"]
        return first[0]["version"], first[1], entries, {(r["version"], r["lo"], r["hi"]): x for r, x in shaped if r["kind"] == "waiting"}


def layout_difference(before: DataFrame, after: DataFrame) -> DataFrame:
    """Pieces of two layouts side by side (a piece that only one has keeps nulls)."""
    a, b = (x.select("worker", "k", F.col("lo").alias(f"lo_{n}"), F.col("hi").alias(f"hi_{n}")) for x, n in ((before, "before"), (after, "after")))
    return a.join(b, ["worker", "k"], "full")
