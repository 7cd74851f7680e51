import random
import re

import numpy as np
import pytest

from stalegrad.llm import minhash_dedup as m
from tests.llm import cases


def shingles(text, size):
    w = re.findall(rb"[^\x20\x09-\x0D]+", bytes(m.LOWER[np.frombuffer((text or "").encode(), dtype=np.uint8)]))
    return {tuple(w[i : i + size]) for i in range(max(1, len(w) - size + 1))} if w else set()


def brute(rows, size, percent):
    ids = [r[0] for r in rows]
    sets = [shingles(r[1], size) for r in rows]
    up = list(range(len(rows)))

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if ids[i] is None or ids[j] is None:
                continue
            both = len(sets[i] & sets[j])
            if sets[i] and sets[j] and (100 * both >= percent * len(sets[i] | sets[j]) or ids[i] == ids[j]):
                up[root(i)] = root(j)
    low = {}
    for i, d in enumerate(ids):
        if d is not None:
            low[root(i)] = min(low.get(root(i), d), d)
    return sorted(((d, len(s), low.get(root(i)) if d is not None else None, d is None or low[root(i)] == d) for i, (d, s) in enumerate(zip(ids, sets, strict=True))), key=str)


def check(spark, rows, size, percent, **options):
    got = sorted((tuple(r) for r in m.near_duplicates(cases.frame(spark, rows), size, percent, **options).collect()), key=str)
    assert got == brute(rows, size, percent)


def test_odd_rows(spark):
    check(spark, cases.odd_rows(), 3, 85)


def test_near_copies_and_chains(spark):
    r = random.Random(3)
    rows, base = [], cases.words(1, 150, 5000)
    for i in range(60):  # a chain: each differs a little from the one before
        base = list(base)
        base[r.randrange(150)] = f"new{i}"
        rows.append((1000 - i, " ".join(base)))
    for i in range(60):
        w = cases.words(50 + i % 6, 80, 3000)
        for _ in range(r.randrange(6)):
            w[r.randrange(80)] = "edit"
        rows.append((2000 + i, " ".join(w).upper()))
    check(spark, rows, 3, 85)
    check(spark, rows, 5, 80)


def test_large_group_with_outliers_in_blocks(spark):
    r = random.Random(9)
    base, rows = cases.words(77, 120, 5000), []
    for i in range(70):
        w = list(base)
        for _ in range(r.choice([1, 2, 4, 9])):
            w[r.randrange(120)] = f"z{r.randrange(40)}"
        rows.append((i, " ".join(w)))
    check(spark, rows, 3, 85)
    check(spark, rows, 3, 85, block=9000)


def test_given_table(spark, sf):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    check(spark, rows, 3, 85)
    got = m.near_duplicates(spark.read.parquet(f"{sf}/documents.parquet"), 3, 85)
    assert 0 < got.where("NOT kept").count() < len(rows) / 2


def test_empty_table_and_extra_columns(spark):
    assert m.near_duplicates(cases.empty(spark)).count() == 0
    docs = cases.frame(spark, cases.odd_rows()).withColumnsRenamed({"lang": "component", "source": "rep"})
    left = m.drop_near(docs)
    assert left.columns == docs.columns and left.where("doc_id = 1").count() == 1


def test_signature_estimates_jaccard():
    rng = np.random.default_rng(0)
    a, b = rng.integers(0, 2**63, 1000, dtype=np.uint64), rng.integers(0, 2**63, 250, dtype=np.uint64)
    x, y = a, np.concatenate((a[250:], b))  # 750 of 1250 shared
    share = (m.signature(x, 250) == m.signature(y, 250)).mean()
    assert abs(share - 0.6) < 0.1


def test_rows_keep_pairs_at_every_threshold():
    assert (m.rows_for(80), m.rows_for(85)) == (5, 7)
    for percent in range(31, 101):
        assert (1 - (percent / 100) ** m.rows_for(percent)) ** m.BANDS <= 1e-8
    with pytest.raises(ValueError):
        m.rows_for(30)


def test_permutations_are_permutations(monkeypatch):
    monkeypatch.setattr(m, "UNIVERSE_BITS", 12)
    for multipliers in (m.SCATTER, m.SHIFTED):
        assert sorted(m.permuted(np.arange(1 << 12), multipliers).tolist()) == list(range(1 << 12))


def test_unrelated_very_long_sets_share_no_band():
    rng = np.random.default_rng(1)
    a, b = (rng.integers(0, 2**63, 1_000_000, dtype=np.uint64) for _ in range(2))
    assert not (m.band_keys(a, m.BANDS, 7) == m.band_keys(b, m.BANDS, 7)).any()


def test_blocks_are_bounded_by_sets_too(spark, monkeypatch):
    monkeypatch.setattr(m, "BLOCK_SETS", 8)
    r, base, rows = random.Random(5), cases.words(5, 40, 5000), []
    for i in range(50):
        w = list(base)
        for _ in range(r.choice([1, 2, 3])):
            w[r.randrange(40)] = f"z{r.randrange(30)}"
        rows.append((i, " ".join(w)))
    check(spark, rows, 3, 85)


def test_clashing_columns(spark):
    docs = cases.frame(spark, cases.odd_rows()).withColumnsRenamed({"lang": "_gone", "source": "kept", "n_chars": "set_key"})
    assert m.drop_near(docs).columns == docs.columns
