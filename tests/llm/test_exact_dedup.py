import hashlib
import random
import re
from collections import defaultdict

import pyarrow as pa

from stalegrad.llm import exact_dedup as x
from tests.llm import cases


def norm(t):
    return re.sub(r"[\x20\x09-\x0D]+", " ", t or "")


def brute(rows):
    groups = defaultdict(list)
    for d, t, *_ in rows:
        groups[norm(t)].append(d)
    out = []
    for d, t, *_ in rows:
        ids = [i for i in groups[norm(t)] if i is not None]
        keep = min(ids) if ids else None
        out.append((d, keep, len(groups[norm(t)]), d == keep, hashlib.sha256(norm(t).encode()).hexdigest()))
    return sorted(out, key=str)


def test_odd_rows(spark):
    rows = cases.odd_rows()
    docs = cases.frame(spark, rows)
    assert sorted((tuple(r) for r in x.exact_groups(docs).collect()), key=str) == brute(rows)
    left = x.drop_exact(docs.withColumnsRenamed({"lang": "digest", "source": "group_size"}))
    assert sorted(norm(r.text) for r in left.collect()) == sorted({norm(r[1]) for r in rows})
    assert x.exact_groups(cases.empty(spark)).count() == 0


def held(index):
    return {(r.keep_id, r.group_size) for r in index.groups().collect()}


def test_index_inserts_and_deletes(spark):
    first = cases.frame(spark, [(1, "a b"), (2, "a  b"), (3, "c"), (4, "d"), (4, "d")])
    second = cases.frame(spark, [(0, "c"), (9, "e")])
    index = x.insert_batch(x.insert_batch(None, first), second)
    assert held(index) == {(1, 2), (0, 2), (4, 2), (9, 1)}
    assert index.keys.where("filter IS NOT NULL").count() >= 1  # the filters are stored
    index = x.delete_batch(index, cases.frame(spark, [(1, "a b"), (4, "d"), (77, "never there"), (77, "e"), (0, "c")]))
    assert held(index) == {(2, 1), (3, 1), (4, 1), (9, 1)}  # the next smallest id stands for the group
    index = x.delete_batch(index, cases.frame(spark, [(4, "d"), (4, "d"), (4, "d")]))
    live = {r.doc_id: r.live for r in x.is_live(index, first.unionByName(second)).collect()}
    assert live == {1: True, 2: True, 3: True, 4: False, 0: True, 9: True}
    assert x.is_live(index, first.withColumnRenamed("lang", "digest")).count() == 5


def test_index_grows_and_is_dealt_anew(spark, monkeypatch):
    docs = [cases.frame(spark, [(i, f"text {i % 700}") for i in range(lo, lo + 500)]) for lo in (0, 500, 1000)]
    monkeypatch.setattr(x, "SHARD_KEYS", 100)
    index = None
    for d in docs:
        index = x.insert_batch(index, d)
    whole = x.exact_groups(docs[0].unionByName(docs[1]).unionByName(docs[2])).select("keep_id", "group_size").distinct()
    assert held(index) == {tuple(r) for r in whole.collect()} and index.shards > 10
    index = x.delete_batch(index, docs[0])
    assert held(index) == {(min(j for j in range(500, 1500) if j % 700 == t), sum(j % 700 == t for j in range(500, 1500))) for t in range(700)}


def test_the_filter_decides(monkeypatch):
    table = pa.table({"digest": [b"k" * 32, b"m" * 32, b"k" * 32], "least": [5, 1, 3], "copies": [2, 1, 4]})
    assert x.absorb(x.CuckooShard(), table).live == {b"k" * 32: [6, 3], b"m" * 32: [1, 1]}
    monkeypatch.setattr(x.CuckooShard, "__contains__", lambda self, key: False)
    assert x.absorb(x.CuckooShard(), table).live != {b"k" * 32: [6, 3], b"m" * 32: [1, 1]}


def test_stored_shard_is_the_same(spark):
    shard = x.CuckooShard(2)
    keys = [hashlib.sha256(str(i).encode()).digest() for i in range(3000)]
    for i, k in enumerate(keys):
        shard.insert(k, 1, i)
    again = x.CuckooShard.load(shard.rows(7))
    assert again.table == shard.table and again.live == shard.live
    assert all(again.delete(k) for k in keys) and not any(m for row in again.table for m in row)


def test_shard_against_a_set():
    r, shard, live = random.Random(1), x.CuckooShard(2), {}
    keys = [hashlib.sha256(str(i).encode()).digest() for i in range(3000)]
    for _ in range(12000):
        k = r.choice(keys)
        if r.random() < 0.6:
            assert shard.insert(k) == (live.get(k, 0) == 0)
            live[k] = live.get(k, 0) + 1
        else:
            last = live.get(k, 0) == 1
            assert shard.delete(k) == last
            live[k] = max(0, live.get(k, 0) - 1)
    assert all((k in shard) == (live.get(k, 0) > 0) for k in keys)
    assert shard.buckets > 2  # it was resized from the stored keys
