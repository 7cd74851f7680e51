import random

import numpy as np
import pyarrow as pa
import pytest

from stalegrad.llm import license_scan as ls
from stalegrad.llm.decontaminate import token_hashes, token_text
from tests.llm import cases


def tokens(text):
    return next((t for _, t in token_hashes(pa.array([token_text(text or "")]))), np.zeros(0, dtype=np.uint64))


def brute(rows, templates, percent=80):
    found = set()
    for d, text, *_ in rows:
        t = tokens(text)
        for name, notice in templates.items():
            n = tokens(notice)
            own = set(ls.shingles(n).tolist())
            size = min(len(n), len(t))
            starts = range(len(t) - size + 1) if size else ()
            if own & set(ls.shingles(t).tolist()) and any(100 * len(own & set(ls.shingles(t[s : s + size]).tolist())) >= percent * len(own) for s in starts):
                found.add((d, name))
    return found


def test_edited_notices_and_odd_rows(spark):
    rows = cases.odd_rows()
    for i, (name, text) in enumerate(sorted(ls.TEMPLATES.items())):
        w = text.split()
        edited = list(w)
        if len(w) > 16:
            edited[5] = "XX"
        rows += [(100 + 3 * i, " ".join(cases.words(i, 30)) + " " + text), (101 + 3 * i, "\n".join(edited).upper() + " " + " ".join(cases.words(i, 9))), (102 + 3 * i, " ".join(w[: len(w) // 2]))]
    got = {(r.doc_id, r.template) for r in ls.scan_licenses(cases.frame(spark, rows)).collect()}
    assert got == brute(rows, ls.TEMPLATES)
    assert {(100 + 3 * i, name) for i, name in enumerate(sorted(ls.TEMPLATES))} <= got


def test_given_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    assert {(r.doc_id, r.template) for r in ls.scan_licenses(docs).collect()} == brute(rows, ls.TEMPLATES)


def test_recall_over_all_offsets(spark):
    """Notices with one word in twenty changed, at any offset: nothing that some window holds is lost."""
    r, rows = random.Random(12), []
    for name, text in sorted(ls.TEMPLATES.items()):
        for _ in range(6):
            w = text.split()
            for at in r.sample(range(len(w)), len(w) // 20):
                w[at] = f"edit{r.randrange(10**6)}"
            rows.append((len(rows), " ".join(cases.words(len(rows), r.randrange(50)) + w + cases.words(len(rows) + 999, r.randrange(50)))))
    got = {(g.doc_id, g.template) for g in ls.scan_licenses(cases.frame(spark, rows)).collect()}
    want = brute(rows, ls.TEMPLATES)
    assert got == want and len({d for d, _ in want}) >= 0.98 * len(rows)


def test_clashing_columns_and_long_text(spark):
    long = " ".join(cases.words(1, 30_000)) + " " + ls.TEMPLATES["mit/grant"]
    docs = cases.frame(spark, [*cases.odd_rows(), (99, long)]).withColumnsRenamed({"lang": "template", "source": "tokens", "n_chars": "license"})
    assert (99, "mit/grant") in {(g.doc_id, g.template) for g in ls.scan_licenses(docs).collect()}


def test_empty(spark):
    assert ls.scan_licenses(cases.empty(spark)).count() == 0
    assert ls.scan_licenses(cases.frame(spark, cases.odd_rows()), {}).count() == 0


def everywhere(t, own, n, percent):
    """Whether some window of n tokens holds the share, over all starts."""
    size = min(n, len(t))
    return any(100 * len(own & set(ls.shingles(t[s : s + size]).tolist())) >= percent * len(own) for s in range(len(t) - size + 1))


@pytest.mark.parametrize("percent", [80, 40])
def test_every_offset_of_edited_notices(spark, percent):
    r = random.Random(percent)
    notices = {f"n/{n}": " ".join(f"t{n}x{i}" for i in range(n)) for n in (9, 16, 18, 24, 30, 60, 200)}
    rows = []
    for n, notice in ((len(x.split()), x) for x in notices.values()):
        for offset in range(40):
            w = notice.split()
            for _ in range(max(1, n * (100 - percent) // 300)):
                w[r.randrange(n)] = f"edit{r.randrange(10**6)}"
            rows.append((len(rows), " ".join(cases.words(len(rows), offset) + w + cases.words(len(rows) + 999, r.randrange(40)))))
    docs = {d: tokens(text) for d, text in rows}
    own = {name: (set(ls.shingles(tokens(x)).tolist()), len(tokens(x))) for name, x in notices.items()}
    want = {(d, name) for d, t in docs.items() for name, (s, n) in own.items() if everywhere(t, s, n, percent)}
    got = ls.scan_licenses(cases.frame(spark, rows), notices, percent).collect()
    assert {(g.doc_id, g.template) for g in got} == want and len(want) > 100
    for g in got:
        window = ls.shingles(docs[g.doc_id][g.first_token : g.first_token + g.n_tokens])
        assert g.n_shared == len(own[g.template][0] & set(window.tolist()))
