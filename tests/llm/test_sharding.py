import zlib
from collections import Counter, defaultdict

from stalegrad.llm import sharding as s
from tests.llm import cases


def check(rows, got, shards=8):
    assert sorted(((r.doc_id, r.size, r.text_crc32, r.source) for r in got), key=str) == sorted(((d, len((t or "").encode()) + 1, zlib.crc32((t or "").encode()), o) for d, t, _, o, _ in rows), key=str)
    by = defaultdict(list)
    for r in got:
        by[r.shard].append(r)
    sizes = [len(by[k]) for k in range(shards)]
    assert max(sizes) - min(sizes) <= 1
    assert all(sorted(r.slot for r in v) == list(range(len(v))) for v in by.values())
    return by


def test_odd_rows_and_few_rows(spark):
    rows = cases.odd_rows()
    check(rows, s.stratified_shards(cases.frame(spark, rows)).collect())
    check(rows[:3], s.stratified_shards(cases.frame(spark, rows[:3])).collect())
    assert s.stratified_shards(cases.empty(spark)).count() == 0


def test_mixture_of_a_hot_source(spark, monkeypatch):
    monkeypatch.setattr(s, "ROWS_PER_BUCKET", 40)
    rows = [(i, f"t{i}", "en", "hot" if i % 3 == 0 else f"s{i % 7}" if i % 5 else f"lone{i}", 1) for i in range(1500)]
    by = check(rows, s.stratified_shards(cases.frame(spark, rows), seed=3).collect())
    whole = Counter(r[3] for r in rows)
    for shard in by.values():
        mix = Counter(r.source for r in shard)
        assert all(abs(mix[k] - n / 8) <= 2.5 for k, n in whole.items())


def test_the_seed_decides(spark):
    docs = cases.frame(spark, [(i, "x", "en", "a", 1) for i in range(200)])
    one, again, other = ({(r.doc_id, r.shard, r.slot) for r in s.stratified_shards(docs.repartition(n), seed=k).collect()} for n, k in ((1, 1), (7, 1), (3, 2)))
    assert one == again != other


def test_written_shards_hold_whole_rows(spark, tmp_path):
    docs = cases.frame(spark, [r for r in cases.odd_rows()])
    s.write_shards(docs, str(tmp_path / "out"), n_shards=4)
    back = spark.read.parquet(str(tmp_path / "out"))
    assert sorted(str(r.text) for r in back.collect()) == sorted(str(r.text) for r in docs.collect())


def test_written_shards_bear_clashing_columns(spark, tmp_path):
    docs = cases.frame(spark, cases.odd_rows()).withColumnsRenamed({"lang": "shard", "n_chars": "slot"}).withColumn("_mark", s.F.lit(1)).withColumn("_copy", s.F.lit("x"))
    s.write_shards(docs, str(tmp_path / "out"), n_shards=4)
    back = spark.read.parquet(str(tmp_path / "out"))
    assert set(back.columns) == {*docs.columns, "_shard", "_slot"} and back.count() == docs.count()
