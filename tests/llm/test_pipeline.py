import corpus_pipeline as p
from stalegrad.llm import language_id as lid
from tests.llm import cases
from tests.llm.test_decontaminate import brute as leak_pairs
from tests.llm.test_exact_dedup import norm
from tests.llm.test_minhash_dedup import brute as near


def test_stages_against_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    schema = docs.schema
    for name, stage in p.STAGES[:-1]:
        rows = [tuple(r) for r in docs.collect()]
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns
        got = sorted(tuple(r) for r in out.collect())
        if name == "language_id":
            kept = {r.doc_id for r in lid.identify(docs).where("NOT rejected").collect()}
        elif name == "exact_dedup":
            kept = {min(r[0] for r in rows if norm(r[1]) == t) for t in {norm(r[1]) for r in rows}}
        elif name == "near_dedup":
            kept = {d for d, _, _, k in near(rows, 5, 80) if k}
        else:
            kept = {r[0] for r in rows} - {d for d, _ in leak_pairs([r[:2] for r in rows], items)}
        assert got == sorted(r for r in rows if r[0] in kept), name
        docs = spark.createDataFrame(got, schema)
    assert p.STAGES[-1][1](spark, docs, sf).select("doc_id").distinct().count() == docs.count()


def test_odd_rows(spark, sf):
    docs = cases.frame(spark, cases.odd_rows())
    for _, stage in p.STAGES[:-1]:
        docs = spark.createDataFrame(stage(spark, docs, sf).collect(), docs.schema)
    assert p.STAGES[-1][1](spark, docs, sf).count() > 0
