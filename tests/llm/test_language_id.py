import zlib

import numpy as np

from stalegrad.llm import language_id as lid
from tests.llm import cases


def test_held_out_accuracy_and_folds(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    truth = {r.doc_id: (r.lang, r.text) for r in docs.collect()}
    got = lid.identify(docs).collect()
    assert len(got) == len(truth)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in got)
    held = [r for r in got if r.held_out and r.lang_pred != "und"]
    assert np.mean([r.lang_pred == truth[r.doc_id][0] for r in held]) > 0.95
    assert all(0 <= r.score <= 1 for r in got)
    assert sum(r.rejected for r in got) < 0.02 * len(got)


def test_odd_rows(spark):
    rows = [(100 + i, " ".join(t.split()[:20]), lang, "s", 1) for i, (t, lang) in enumerate([("the of and in to that is", "en"), ("der die und in den von zu", "de")] * 20)]
    docs = cases.frame(spark, cases.odd_rows() + rows)
    got = {(r.doc_id, r.lang_pred) for r in lid.identify(docs).collect()}
    assert {(1, "und"), (2, "und"), (3, "und")} <= got
    assert lid.identify(cases.empty(spark)).count() == 0
    unlabelled = cases.frame(spark, [(1, "some words", None, None, 1)])
    assert lid.identify(unlabelled).first().lang_pred == "und"


def test_stage_keeps_columns(spark):
    docs = cases.frame(spark, cases.odd_rows()).withColumnsRenamed({"source": "score", "n_chars": "rejected"})
    kept = lid.keep_identified(docs)
    assert kept.columns == docs.columns
    assert {r.doc_id for r in kept.collect()}.isdisjoint({1, 2, 3})


def test_gradient_training_separates():
    texts = [b"aaa aaa bbb" if i % 2 else b"xxx yyy zzz" for i in range(100)]
    model = lid.train(texts, ["p" if i % 2 else "q" for i in range(100)])
    assert model.languages[int(model.probabilities(np.frombuffer(b"aaa", dtype=np.uint8)).argmax())] == "p"


def test_sample_is_of_distinct_texts_of_every_language(spark, monkeypatch):
    rows = [(i, f"text number {i}", "en" if i % 300 else "fr", "s", 1) for i in range(3000)]
    copies = [(10_000 + i, f"copied {i % 40}", "en", "s", 1) for i in range(40 * 150)]
    seen = {}
    monkeypatch.setattr(lid, "train", lambda texts, labels: seen.update(texts=texts, labels=labels))
    lid.fit(cases.frame(spark, rows + copies), max_rows=100)
    assert len(seen["texts"]) == len(set(zip(seen["texts"], seen["labels"], strict=True))) == 100
    assert seen["labels"].count("fr") == 10  # all there are


def test_long_texts_are_passed_over(spark, monkeypatch):
    rows = [(i, f"text {i}" + " long" * (400 if i % 2 else 0), "en" if i % 4 else "fr", "s", 1) for i in range(200)]
    seen = {}
    monkeypatch.setattr(lid, "train", lambda texts, labels: seen.update(texts=texts, labels=labels))
    lid.fit(cases.frame(spark, rows), max_rows=150, max_bytes=4000)
    assert sum(len(t) < 20 for t in seen["texts"]) == 100
    assert sum(map(len, seen["texts"])) <= 4000
    assert {"en", "fr"} == set(seen["labels"])


def test_every_language_is_trained_on():
    single = [c * 3 + b" " + c * 4 for c in (bytes([x]) for x in b"cdefghijkl")]
    model = lid.train([b"aaa bbb"] * 10 + single, ["p"] * 10 + [t.decode()[0] for t in single], epochs=100)
    for text in single:
        assert model.languages[int(model.probabilities(np.frombuffer(text, dtype=np.uint8)).argmax())] == text.decode()[0]


def fitted(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    held = [r for r in docs.collect() if r.text and r.lang and zlib.crc32(str(r.doc_id).encode()) % 5 == 0]
    return docs, lid.fit(lid.learnable(docs)), [(np.frombuffer(r.text.encode(), dtype=np.uint8), r.lang) for r in held]


def test_rejection_and_calibration(spark):
    _, model, held = fitted(spark)
    judged = [(*model.judge(t), model.threshold(len(t)), lang) for t, lang in held]
    assert np.mean([known < least for _, known, least, _ in judged]) <= 0.01  # clean texts stay
    sure = np.array([p.max() for p, *_ in judged])
    right = np.array([model.languages[int(p.argmax())] == lang for p, _, _, lang in judged])
    error = sum(abs(sure[x].mean() - right[x].mean()) * x.mean() for lo in np.arange(0, 1, 0.1) if (x := (sure > lo) & (sure <= lo + 0.1)).any())
    assert error < 0.02
    rng = np.random.default_rng(3)
    junk = [rng.permutation(t[t > 64]) for t, _ in held if len(t) > 200]
    assert np.mean([model.judge(t)[1] < model.threshold(len(t)) for t in junk]) > 0.95


FOREIGN = (
    "Wszyscy ludzie rodza sie wolni i rowni pod wzgledem swej godnosci i swych praw. Sa oni obdarzeni rozumem i sumieniem",
    "Kaikki ihmiset syntyvat vapaina ja tasavertaisina arvoltaan ja oikeuksiltaan. Heille on annettu jarki ja omatunto",
    "zqxj kvwp qqzx jjkw vbnm xzcv wqpz kjhg zxkq wvjb qjxz kkvw zzqp",
)


def test_foreign_text_is_rejected(spark):
    docs, _, _ = fitted(spark)
    more = docs.unionByName(cases.frame(spark, [(10**7 + i, t) for i, t in enumerate(FOREIGN)]))
    kept = {r.doc_id for r in lid.keep_identified(more).select("doc_id").collect()}
    assert kept.isdisjoint({10**7 + i for i in range(len(FOREIGN))}) and len(kept) > 0.97 * docs.count()


def test_prediction_is_the_mean_over_all_subwords(spark):
    docs, model, _ = fitted(spark)
    got = {r.doc_id: r for r in lid.predict(docs, model, ["doc_id"]).collect()}
    for r in docs.limit(200).collect():
        if not any(c.isalpha() for c in r.text or ""):
            assert got[r.doc_id].lang_pred == "und"
            continue
        text = b" " + bytes(b | 32 if 65 <= b <= 90 else b if b > 127 or 97 <= b <= 122 else 32 for b in r.text.encode()) + b" "
        grams = [text[i : i + n] for n in (3, 4) for i in range(len(text) - n + 1)]
        at = [((int.from_bytes(g, "little") + (1 << 40 if len(g) == 4 else 0)) * 0x9E3779B97F4A7C15 % (1 << 64)) >> 49 for g in grams if g.strip(b" ")]
        z = (np.mean([model.scores[i] for i in at], axis=0) + model.bias) * model.sharpness
        p = np.exp(z[:-1] - z[:-1].max())
        assert got[r.doc_id].lang_pred == model.languages[int(p.argmax())] and abs(got[r.doc_id].score - p.max() / p.sum()) < 1e-6
