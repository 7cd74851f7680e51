import hashlib
import random
from collections import Counter

import numpy as np
import pytest

from stalegrad.llm.prefix_free import common_prefix, repeated_starts, suffix_order
from stalegrad.llm.suffix_dedup import remove_repeats
from tests.llm import cases


def brute(rows, width):
    texts = [(r[0], (r[1] or "").encode()) for r in rows]
    count = Counter(t[i : i + width] for _, t in texts for i in range(len(t) - width + 1))
    out = []
    for d, t in texts:
        gone = np.zeros(len(t), dtype=bool)
        for i in range(len(t) - width + 1):
            if count[t[i : i + width]] > 1:
                gone[i : i + width] = True
        spans = int((np.diff(np.concatenate(([0], gone.astype(int)))) == 1).sum())
        kept = bytes(b for b, g in zip(t, gone, strict=True) if not g)
        out.append((d, len(t), int(gone.sum()), spans, hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=str)


def check(spark, rows, width, **options):
    got = [tuple(r)[:5] for r in remove_repeats(cases.frame(spark, rows), width, **options).collect()]
    assert sorted(got, key=str) == brute(rows, width)


def mixed_rows():
    r = random.Random(8)
    passages = [" ".join(cases.words(700 + i, 30 + 40 * i, 60)) for i in range(5)]
    rows = []
    for i in range(40):
        parts = [" ".join(cases.words(r.randrange(10**6), r.randrange(60), 40)) + r.choice(passages)[r.randrange(40) :] for _ in range(r.randrange(4))]
        rows.append((i, "".join(parts)))
    return rows + [(50, "x" * 2500), (51, "é" * 300 + "ab" * 700), (None, passages[4])]


def test_odd_rows(spark):
    check(spark, cases.odd_rows(), 400)


@pytest.mark.parametrize("part_bytes", [512 << 10, 1500])
def test_mixed_rows(spark, part_bytes):
    check(spark, mixed_rows(), 400, part_bytes=part_bytes)


def test_given_table(spark, sf):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    check(spark, rows, 400)


def test_empty_table(spark):
    assert remove_repeats(cases.empty(spark)).count() == 0


def test_suffix_order_and_twins_against_sorting():
    r = random.Random(2)
    for _ in range(60):
        letters = r.choice([b"a", b"ab", bytes(range(256))])
        base = [bytes(r.choice(letters) for _ in range(r.randrange(200))) for _ in range(4)]
        strings = [b"".join(r.choice(base)[r.randrange(5) :] for _ in range(r.randrange(4))) for _ in range(r.randrange(1, 8))]
        data = np.frombuffer(b"".join(strings), dtype=np.uint8)
        offs = np.concatenate(([0], np.cumsum([len(s) for s in strings])))
        suffixes = [s[i:] for s in strings for i in range(len(s))]
        order = suffix_order(data, offs)
        assert all(suffixes[a] <= suffixes[b] for a, b in zip(order, order[1:]))
        for width in (5, 40):
            count = Counter(x[:width] for x in suffixes if len(x) >= width)
            assert repeated_starts(data, offs, width).tolist() == [len(x) >= width and count[x[:width]] > 1 for x in suffixes]


def test_common_prefix_is_of_bytes():
    rng = np.random.default_rng(4)
    data = np.concatenate([rng.integers(0, 2, 300), np.tile(rng.integers(0, 2, 40), 8)]).astype(np.uint8)
    for width in (1, 7, 30):
        last = len(data) - width
        a = np.sort(rng.integers(0, last, 5000))
        b = np.where(rng.random(5000) < 0.5, np.minimum(a + 40, last), rng.integers(0, last, 5000))
        want = [bytes(data[i : i + width]) == bytes(data[j : j + width]) for i, j in zip(a, b, strict=True)]
        assert common_prefix(data, a, b, width).tolist() == want
        a = np.arange(last - 40)
        assert common_prefix(data, a, a + 40, width).tolist() == [bytes(data[i : i + width]) == bytes(data[i + 40 : i + 40 + width]) for i in a]
