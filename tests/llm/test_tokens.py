import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from stalegrad.llm import tokens as t
from tests.llm import cases

PATH = t.tokenizer_path()


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(PATH)
    tok.encode_special_tokens = True
    return lambda text: tok.encode(text or "", add_special_tokens=False).ids


def test_same_ids_as_the_library(library, spark, sf):
    texts = [r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    texts += ["", "  a\n\n b  ", "x<|endoftext|>y", "é ü\x1c\x85 1²½ ́a 中文 🙂\r\n\t", "   ", "it's I'LL 's"]
    assert all(t.encoder(PATH)(x) == library(x) for x in texts)


def test_histogram_answers(spark, library):
    rows = cases.odd_rows()
    lengths = [len(library(r[1])) for r in rows]
    got = t.length_histogram(t.token_lengths(cases.frame(spark, rows).select("text"), PATH))
    want = []
    for n, k in sorted(Counter(lengths).items()):
        want.append((n, k, sum(x >= n for x in lengths), sum(x for x in lengths if x >= n), sum(x < n for x in lengths), sum(x for x in lengths if x < n), sum(min(x, n) for x in lengths)))
    assert sorted(map(tuple, got.collect())) == want
    cut = {r.context_limit: (r.truncated_tokens, r.docs_cut) for r in t.truncated_totals(got, [1, 100, 10**6]).collect()}
    assert cut == {c: (sum(min(x, c) for x in lengths), sum(x > c for x in lengths)) for c in (1, 100, 10**6)}
    q = {r.level: r.n_tokens for r in t.quantiles(got, [0.0, 0.5, 1.0]).collect()}
    assert q[1.0] == max(lengths) and q[0.5] == sorted(lengths)[(len(lengths) + 1) // 2 - 1]
    assert t.length_histogram(t.token_lengths(cases.empty(spark), PATH)).count() == 0


def test_packing_round_trip(spark, library):
    rows = cases.odd_rows()
    rows += [(500 + i, " ".join(cases.words(i, random.Random(i).randrange(1, 1400))), "en", "s", 1) for i in range(60)]
    got = t.pack(cases.frame(spark, rows), PATH).collect()
    by_doc, seqs = defaultdict(list), defaultdict(list)
    for r in got:
        by_doc[r.doc_id].append(r)
        seqs[r.sequence_id].append((r.offset, r.length))
    for d, text, *_ in rows:
        ids = np.array([*library(text), 2], dtype="<u4")
        copies = sum(r[0] == d and r[1] == text for r in rows)
        mine = [r for r in by_doc[d] if zlib.crc32(ids[r.start : r.start + r.length].tobytes()) == r.ids_crc32]
        assert sum(r.length for r in mine) == copies * len(ids)
        assert all(r.length == 1024 for r in mine if r.piece)
    for places in seqs.values():
        at = 0
        for o, n in sorted(places):
            assert o == at
            at += n
        assert at <= 1024
    total = sum(r.length for r in got)
    assert len(seqs) <= 1.02 * -(-total // 1024) + 1
    assert t.pack(cases.empty(spark), PATH).count() == 0


def test_plan_is_best_fit():
    rnd = random.Random(1)
    for _ in range(60):
        limit = rnd.choice([5, 16, 64])
        counts = {rnd.randint(1, limit): rnd.choice([1, 2, 3, 7, 50]) for _ in range(rnd.randint(1, 20))}
        room = []
        for n in sorted(counts, reverse=True):
            for _ in range(counts[n]):
                fits = [i for i, r in enumerate(room) if r >= n]
                if fits:
                    room[min(fits, key=lambda i: room[i])] -= n
                else:
                    room.append(limit - n)
        plan, bins = t.best_fit_plan(counts, limit), Counter()
        for n, lo, hi, per, first, _ in plan:
            for r in range(lo, hi):
                bins[first + (r - lo) // per] += n
        assert len(bins) == len(room) and max(bins.values()) <= limit
