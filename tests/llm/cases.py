"""Small tables with every edge the operators must bear."""

from __future__ import annotations

import random

from pyspark.sql import DataFrame, SparkSession

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def frame(spark: SparkSession, rows: list[tuple], schema: str = SCHEMA) -> DataFrame:
    full = [tuple(r) + (None,) * (5 - len(r)) if len(r) < 5 else tuple(r) for r in rows]
    return spark.createDataFrame(full, schema)


def empty(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([], SCHEMA)


def words(seed: int, n: int, vocabulary: int = 400) -> list[str]:
    r = random.Random(seed)
    return [f"w{r.randrange(vocabulary)}" for _ in range(n)]


def odd_rows() -> list[tuple]:
    """Nulls, empties, ties, repeated rows, white space, a very long text."""
    base = " ".join(words(1, 120))
    return [
        (1, None, None, None, None),
        (2, "", "en", "a", 0),
        (3, "   \t\n ", "en", "a", 6),
        (4, base, "en", "a", 5),
        (5, base, "en", None, 5),
        (6, base.replace(" ", "\n\n"), "fr", "b", 5),
        (6, base.replace(" ", "\n\n"), "fr", "b", 5),
        (7, " ".join(words(1, 120)[:70] + words(2, 60)), None, "b", 5),
        (8, " ".join(words(3, 30) + words(1, 120)[20:]), "de", "c", 5),
        (9, " ".join(words(4, 6000)), "es", "c", 5),
        (10, " ".join(words(4, 6000)[:5990] + ["x"]), "es", "c", 5),
        (None, base, "en", "a", 5),
        (11, "one", "en", "a", 3),
        (12, "one two", "en", "a", 7),
        (13, "Ä 中文 🙂 é", "de", "a", 7),
        (14, "ab" * 900, "en", "a", 7),
    ]
