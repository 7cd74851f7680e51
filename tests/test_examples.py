"""Worked examples and invariants of row ranges, alignment and the cache."""

import random

import numpy as np
import pytest

from stalegrad.operators.cache import IntervalCache
from stalegrad.operators.partitioning import align, next_sub, sub_bounds, translate


def test_bounds_of_ten_rows():
    assert [sub_bounds(10, 3, k) for k in (1, 2, 3)] == [(1, 3), (4, 6), (7, 10)]
    with pytest.raises(ValueError):
        sub_bounds(3, 4, 1)


def test_pieces_tile_the_rows():
    for m in range(1, 40):
        for q in range(1, m + 1):
            b = [sub_bounds(m, q, k) for k in range(1, q + 1)]
            assert b[0][0] == 1 and b[-1][1] == m
            assert all(x[1] + 1 == y[0] for x, y in zip(b, b[1:]))
            sizes = {y - x + 1 for x, y in b}
            assert max(sizes) - min(sizes) <= 1


def test_translate_brackets_the_start():
    for m in range(1, 30):
        for p in range(1, m + 1):
            for q in range(1, m + 1):
                for k in range(1, p + 1):
                    j, s = translate(m, p, q, k), sub_bounds(m, p, k)[0]
                    assert sub_bounds(m, q, j)[0] <= s <= sub_bounds(m, q, j)[1]


def test_alignment_examples():
    assert align(10, 2, 3, 1) == 1
    assert align(10, 2, 4, 1) == 3  # both start on row 6
    assert align(10, 4, 2, 1) == 1  # would step below the first piece


@pytest.mark.parametrize("mode", ["walk", "nearest"])
def test_alignment_is_aligned(mode):
    for m in range(1, 24):
        for p in range(1, m + 1):
            for q in range(1, m + 1):
                for k in range(1, p + 1):
                    j = align(m, p, q, k, mode)
                    assert 1 <= j <= q
                    assert sub_bounds(m, q, j)[0] in {sub_bounds(m, p, i)[0] for i in range(1, p + 1)}


def test_nearest_is_never_behind_the_walk():
    assert all(align(24, p, q, k, "nearest") >= align(24, p, q, k) for p in range(1, 13) for q in range(1, 13) for k in range(1, p + 1))
    assert align(24, 4, 6, 2, "restart") == 1 and align(24, 4, 6, 2, "none") == 3


def test_eviction_example():
    c = IntervalCache()
    c.offer(1, 5, 1)
    c.offer(6, 10, 2)
    e = c.offer(4, 6, 3)
    assert e.action == "replace" and sorted(x[:2] for x in e.evicted) == [(1, 5), (6, 10)] and c.rows == 3


def test_same_version_and_containing_interval_block():
    c = IntervalCache()
    c.offer(1, 10, 4)
    assert c.offer(3, 4, 4).action == "reject" and c.offer(3, 4, 3).action == "reject"
    assert c.offer(3, 4, 5).action == "replace" and c.rows == 2
    blind = IntervalCache("endpoint")
    blind.offer(1, 10, 4)
    assert blind.offer(3, 4, 3).action == "insert" and blind.rows == 12  # the ablation counts rows twice


def test_cache_against_a_row_map():
    r, rng = random.Random(3), np.random.default_rng(0)
    c, held = IntervalCache(), {}
    for step in range(3000):
        parts = r.choice([2, 3, 5, 8])
        lo, hi = sub_bounds(60, parts, r.randrange(parts) + 1)
        version, g = r.randrange(step // 10 + 2), rng.normal(size=(3, 1))
        hits = {v for v in held.values() if v[0] <= hi and v[1] >= lo}
        want = "reject" if any(v[2] >= version for v in hits) else "replace" if hits else "insert"
        before = {k: v[2] for k, v in held.items()}
        assert c.offer(lo, hi, version, g).action == want
        if want != "reject":
            held = {row: v for row, v in held.items() if v not in hits} | {row: (lo, hi, version, g.tobytes()) for row in range(lo, hi + 1)}
        assert c.rows == len(held) == sum(e.hi - e.lo + 1 for e in c.entries)
        assert all(a.hi < b.lo for a, b in zip(c.entries, c.entries[1:]))
        assert all(held[k][2] >= v for k, v in before.items() if k in held)
    total = np.sum([np.frombuffer(v[3]).reshape(3, 1) for v in set(held.values())], axis=0)
    assert np.allclose(c.total, total, atol=1e-9)
    c.resum()
    assert np.allclose(c.total, total, atol=1e-12)


def test_cyclic_counter():
    k, seen = 3, []
    for _ in range(4):
        k = next_sub(k, 3)
        seen.append(k)
    assert seen == [1, 2, 3, 1]
