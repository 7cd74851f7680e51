import random
from itertools import combinations

import numpy as np

from stalegrad.llm import decontaminate as d
from tests.llm import cases


def brute(docs, items, min_tokens=13, percent=80):
    """Item-document pairs with a good enough aligned stretch, by trying every diagonal and stretch."""
    number: dict[str, int] = {}
    found = set()
    split = [(k, np.array([number.setdefault(w, len(number)) for w in d.token_text(t or "").split()])) for k, t in items]
    for i, text in docs:
        a = np.array([number.get(w, -1) for w in d.token_text(text or "").split()])
        for k, b in split:
            if not len(b):
                continue
            need = min(min_tokens, len(b))
            for shift in range(-len(b) + need, len(a) - need + 1):
                lo, hi = max(0, -shift), min(len(b), len(a) - shift)
                same = a[lo + shift : hi + shift] == b[lo:hi]
                if (i, k) in found or 100 * same.sum() < percent * need:
                    continue
                for x in np.flatnonzero(same):
                    for y in range(x + need, len(same) + 1):
                        if 100 * same[x:y].sum() >= percent * (y - x) and same[y - 1]:
                            found.add((i, k))
    return found


def leaks(spark, docs, items, **options):
    left = cases.frame(spark, docs)
    right = spark.createDataFrame(items, "item_id long, text string")
    return {(r.doc_id, r.item_id) for r in d.leaks(left, right, **options).collect()}


def test_substitutions_within_the_masks(spark):
    item = cases.words(1, 13, 10**6)
    docs = []
    for n, bad in enumerate(combinations(range(1, 12), 2)):
        w = list(item)
        for b in bad:
            w[b] = "changed"
        docs.append((n, " ".join(cases.words(n + 50, 20) + w + cases.words(n + 500, 20))))
    found = leaks(spark, docs, [(7, " ".join(item).upper())])
    assert found == {(i, 7) for i, _ in docs} == brute(docs, [(7, " ".join(item))])


def test_against_brute_force_broadcast_and_joined(spark, monkeypatch):
    r = random.Random(4)
    items = [(k, " ".join(cases.words(k, r.choice([4, 9, 14, 30])))) for k in range(12)] + [(90, None), (91, ""), (92, "...")]
    docs = []
    for i in range(40):
        w = cases.words(1000 + i, 30)
        if i % 2:
            text = r.choice(items[:12])[1].split()
            cut = text[: max(4, len(text) - r.randrange(12))]
            w += cut
        docs.append((i, ", ".join(w + cases.words(2000 + i, 10))))
    want = brute(docs, items)
    assert leaks(spark, docs, items) == want and want
    left, right = cases.frame(spark, docs), spark.createDataFrame(items, "item_id long, text string")
    for bits in (26, 10):  # a full bit table lets everything through, with the same rows
        monkeypatch.setattr(d, "FILTER_BITS", bits)
        assert {(r.doc_id, r.item_id) for r in d.leaks(left, right, block_hashes=100).collect()} == want
    rows = sorted(map(tuple, d.leaks(left, right).collect()))
    assert sorted(map(tuple, d.leaks(left, right, block_hashes=100).collect())) == rows
    assert {r.doc_id for r in d.drop_leaks(left, right, block_hashes=100).collect()} == {i for i, _ in docs} - {i for i, _ in want}


def test_odd_rows_and_stage(spark):
    docs = cases.frame(spark, [r for r in cases.odd_rows()]).withColumnsRenamed({"lang": "item_id", "source": "leaks"})
    items = spark.createDataFrame([(1, " ".join(cases.words(1, 40)))], "item_id long, text string")
    left = d.drop_leaks(docs, items)
    assert left.columns == docs.columns
    assert sorted(str(r.doc_id) for r in left.collect()) == sorted(map(str, [1, 2, 3, 9, 10, 11, 12, 13, 14]))
    assert d.leaks(cases.empty(spark), items).count() == 0
    none = spark.createDataFrame([], "item_id long, text string")
    assert d.leaks(docs, none).count() == 0 and d.drop_leaks(docs, none).count() == docs.count()


def test_every_placing_meets_a_mask():
    for length in range(13, 26):  # a longer stretch holds one of these with the same share
        places = [sum(1 << (o + j) for j, c in enumerate(m) if c == "1") for m in d.MASKS for o in range(length - d.SPAN + 1)]
        missed = [c for c in combinations(range(length), length * (100 - d.PERCENT) // 100) if all(p & sum(1 << x for x in c) for p in places)]
        assert not missed, (length, missed)


def test_repetitive_text_against_repetitive_item(spark):
    docs = [(1, "la " * 3000), (2, "la " * 12), (3, " ".join(cases.words(3, 50)))]
    assert leaks(spark, docs, [(5, "la " * 400)]) == {(1, 5)}
    block = d.build_block([(5, "la " * 400)])
    doc = next(t for _, t in d.token_hashes(d.pa.array(["la " * 3000])))
    assert len(d._diagonals(doc, block)) <= 3400
    assert d.scan(doc, block, 13, 80)[0][4] == 400


def test_only_the_tokens_go_to_python(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    plan = d.drop_leaks(docs, spark.read.parquet(f"{sf}/benchmark.parquet"))._jdf.queryExecution().executedPlan().toString()
    assert "ArrowEvalPython" in plan and "MapInArrow" not in plan
