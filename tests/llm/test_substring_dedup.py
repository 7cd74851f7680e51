import hashlib
import random
import re

from stalegrad.llm.substring_dedup import remove_repeats, repeat_levels
from tests.llm import cases


def brute(rows, window):
    split = [(i, re.findall(r"[^\x20\x09-\x0D]+", t or "")) for i, t, *_ in rows]
    first = {}
    for i, w in split:
        if i is not None:
            for p in range(len(w) - window + 1):
                k = tuple(w[p : p + window])
                first[k] = min(first.get(k, i), i)
    out = []
    for i, w in split:
        gone = set()
        if i is not None:
            for p in range(len(w) - window + 1):
                if first[tuple(w[p : p + window])] < i:
                    gone.update(range(p, p + window))
        kept = " ".join(x for p, x in enumerate(w) if p not in gone)
        out.append((i, len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return sorted(out, key=str)


def check(spark, rows, window):
    got = [tuple(r)[:4] for r in remove_repeats(cases.frame(spark, rows), window).collect()]
    assert sorted(got, key=str) == brute(rows, window)


def test_odd_rows(spark):
    check(spark, cases.odd_rows(), 50)


def test_shared_passages_and_ties(spark):
    r = random.Random(5)
    passages = [cases.words(100 + i, 20 + 15 * i, 50) for i in range(6)]
    rows = []
    for i in range(40):
        w = []
        for _ in range(r.randrange(5)):
            w += cases.words(r.randrange(10**6), r.randrange(40), 30) + r.choice(passages)[r.randrange(10) :]
        rows.append((r.randrange(30), " ".join(w)))
    check(spark, rows, 50)
    check(spark, rows, 10)


def test_given_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    got = sorted((tuple(r)[:4] for r in remove_repeats(docs).collect()), key=str)
    assert got == brute(rows, 50)
    assert sum(x[2] for x in got) > 0


def test_empty_table(spark):
    assert remove_repeats(cases.empty(spark)).count() == 0


def test_levels_end(spark):
    base = cases.words(1, 130)
    rows = [(1, " ".join(base)), (2, " ".join(["a", *base])), (3, " ".join(cases.words(2, 90)))]
    levels = [tuple(r) for r in repeat_levels(cases.frame(spark, rows), 50).collect()]
    assert levels == [(50, 162, 2), (100, 62, 2)]
