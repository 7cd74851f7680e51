"""Benchmark decontamination by spaced seeds.

A mask is a span of ``SPAN`` tokens of which only some positions count.  Test
and training windows that agree on the counted positions of any mask meet by
hash, so a substitution at an ignored position does not hide them.  Each meeting
gives a diagonal (training place minus test place); along it the tokens of both
texts are compared one by one, and the best stretch that holds the hit decides:
a leak is an aligned stretch of at least ``min_tokens`` tokens (the whole item
if it is shorter) of which at least ``percent`` in a hundred agree.

Tokens are the runs of letters and digits of the lower-cased text, so case,
punctuation and white space do not matter.

Test and training seeds are joined on their hash.  A test side of at most about
``block_hashes`` seeds, a documented bound, is broadcast as one sorted table, and
the training side is not shuffled.  A larger one stays distributed: a bit table of
fixed size over its seeds drops nearly all training seeds, the others and the
distributed test seeds meet in a shuffled join, and only the distinct diagonals
come back to the tokens of their texts.  Both ways give the same rows.

Edge cases: null, empty and token-free texts hold no leak; null items are
ignored; items shorter than ``SPAN`` tokens use their whole length as one exact
seed; repeated items give one row each.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stalegrad.llm.common import written
from stalegrad.llm.kernels import U64, blocks, mix, word_codes, word_spans

SPAN = 10
#: The counted positions of each mask.
MASKS = ("1111011000", "1101100101", "0110010111", "1011000111", "1110101001", "0001101111")
MIN_TOKENS, PERCENT = 13, 80
_FILTER = 1 << 22
FILTER_BITS = 26
_PAIRS = 1 << 18

_TOKEN = re.compile(r"[^\W_]+")


def token_column(text: Column) -> Column:
    """The tokens of a text, lower-cased and parted by one space, made in the JVM."""
    return F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+", " ")


def token_text(text: str) -> str:
    """The same for a single text of the driver."""
    return " ".join(_TOKEN.findall(text.lower()))


def token_hashes(column: pa.Array) -> Iterator[tuple[int, np.ndarray]]:
    """(row, 64-bit hash of each token) for a column of parted tokens."""
    for lo, hi, data, offs in blocks(column):
        start, end, first = word_spans(data, offs)
        codes = word_codes(data, start, end, lane=0)
        for r in range(hi - lo):
            yield lo + r, codes[first[r] : first[r + 1]]


def seed_hashes(tokens: np.ndarray, mask: int) -> np.ndarray:
    """The hash of each span of a text under one mask."""
    n = len(tokens) - SPAN + 1
    if n < 1:
        return np.zeros(0, dtype=np.uint64)
    out = np.full(n, mask + 1, dtype=np.uint64)
    for j, counted in enumerate(MASKS[mask]):
        if counted == "1":
            out = out * U64(0x9E3779B97F4A7C15) + tokens[j : j + n]
    return mix(out)


@dataclass
class Block:
    """Seeds of some items, sorted by hash, and a small filter before the search."""

    ids: list[int]
    tokens: list[np.ndarray]
    hashes: np.ndarray
    owner: np.ndarray
    place: np.ndarray
    kind: np.ndarray
    filter: np.ndarray
    short: list[int]


def build_block(items: list[tuple[int, str]]) -> Block:
    """A block of (item_id, parted tokens)."""
    ids, tokens, parts, short = [], [], [], []
    for i, t in token_hashes(pa.array([text for _, text in items], pa.string())):
        if not len(t):
            continue
        k = len(ids)
        ids.append(items[i][0])
        tokens.append(t)
        if len(t) < SPAN:
            short.append(k)
        for m in range(len(MASKS)):
            h = seed_hashes(t, m)
            parts.append((h, np.full(len(h), k), np.arange(len(h)), np.full(len(h), m)))
    cols = [np.concatenate(c) if parts else np.zeros(0, dtype=np.int64) for c in zip(*parts, strict=True)] if parts else [np.zeros(0, dtype=np.uint64), *[np.zeros(0, dtype=np.int64)] * 3]
    order = np.argsort(cols[0], kind="stable")
    table = np.zeros(_FILTER, dtype=bool)
    table[(cols[0] & U64(_FILTER - 1)).astype(np.int64)] = True
    return Block(ids, tokens, *(c[order] for c in cols), filter=table, short=short)


def _stretch(agree: np.ndarray, percent: int) -> tuple[int, int]:
    """Longest stretch of one diagonal, beginning and ending in agreement, with enough of it."""
    score = np.concatenate(([0], np.cumsum(np.where(agree, 100 - percent, -percent))))
    best = (0, 0)
    low = np.minimum.accumulate(score)
    for end in np.flatnonzero(agree) + 1:
        # the earliest start whose score is not above the end's: running minima fall
        start = int(np.searchsorted(-low, -score[end], side="left"))
        while start < end and not agree[start]:
            start += 1
        if end - start > best[1] - best[0]:
            best = (start, int(end))
    return best


def _diagonals(doc: np.ndarray, block: Block) -> list[tuple[int, int]]:
    """Distinct (item, shift) at which a seed of the text meets one of the block, expanded a bounded number at a time."""
    found = np.zeros(0, dtype=np.int64)
    for m in range(len(MASKS)):
        h = seed_hashes(doc, m)
        at = np.flatnonzero(block.filter[(h & U64(_FILTER - 1)).astype(np.int64)])
        if not len(at) or not len(block.hashes):
            continue
        lo, hi = np.searchsorted(block.hashes, h[at], "left"), np.searchsorted(block.hashes, h[at], "right")
        met = hi > lo
        at, lo, size = at[met], lo[met], (hi - lo)[met]
        total = np.concatenate(([0], np.cumsum(size)))
        i = 0
        while i < len(at):
            j = max(i + 1, int(np.searchsorted(total, total[i] + _PAIRS, side="right")) - 1)
            k = np.repeat(lo[i:j] - total[i:j], size[i:j]) + np.arange(total[i], total[j])
            mine = block.kind[k] == m
            shift = np.repeat(at[i:j], size[i:j])[mine] - block.place[k[mine]]
            found = np.union1d(found, block.owner[k[mine]] * (1 << 32) + shift + (1 << 31))
            i = j
    out = [(int(x >> 32), int(x & 0xFFFFFFFF) - (1 << 31)) for x in found.tolist()]
    for k in block.short:
        item = block.tokens[k]
        same = np.ones(max(0, len(doc) - len(item) + 1), dtype=bool)
        for j, t in enumerate(item):
            same &= doc[j : j + len(same)] == t
        out += [(k, p) for p in np.flatnonzero(same).tolist()]
    return out


def best_stretch(doc: np.ndarray, item: np.ndarray, shifts: list[int], min_tokens: int, percent: int) -> tuple[int, int, int, int] | None:
    """(document token, item token, length, agreeing) of the stretch with most agreement over the given diagonals."""
    best, need = None, min(min_tokens, len(item))
    for shift in shifts:
        lo, hi = max(0, -shift), min(len(item), len(doc) - shift)
        agree = doc[lo + shift : hi + shift] == item[lo:hi]
        if 100 * int(agree.sum()) < percent * need or (best is not None and int(agree.sum()) <= best[3]):
            continue
        a, b = _stretch(agree, percent)
        same = int(agree[a:b].sum())
        if b - a >= need and (best is None or same > best[3]):
            best = (lo + shift + a, lo + a, b - a, same)
    return best


def scan(doc: np.ndarray, block: Block, min_tokens: int, percent: int) -> list[tuple[int, int, int, int, int]]:
    """(item, document token, item token, length, agreeing) of the best leak of each item in a tokenised text."""
    shifts: dict[int, list[int]] = {}
    for k, shift in _diagonals(doc, block):
        shifts.setdefault(k, []).append(shift)
    out = []
    for k in sorted(shifts):
        best = best_stretch(doc, block.tokens[k], shifts[k], min_tokens, percent)
        if best:
            out.append((block.ids[k], *best))
    return out


def _clean(items: DataFrame) -> DataFrame:
    return items.where("item_id IS NOT NULL AND text IS NOT NULL").select(F.col("item_id").cast("long").alias("item_id"), token_column(F.col("text")).alias("tokens"))


def _block(items: DataFrame, block_hashes: int) -> Block | None:
    """The test side as one block, or None above the bound; a token and its gap are two bytes at least."""
    size = items.agg(F.sum(F.octet_length("tokens"))).first()[0] or 0
    if size * len(MASKS) > 2 * block_hashes:
        return None
    return build_block([(r["item_id"], r["tokens"]) for r in items.collect()])


def _seeds(tokens: np.ndarray, lengths: list[int]) -> Iterator[tuple[int, np.ndarray]]:
    """(kind, hashes): spans under each mask, and whole runs of each of the short lengths."""
    for m in range(len(MASKS)):
        yield m, seed_hashes(tokens, m)
    for length in lengths:
        out = np.full(max(0, len(tokens) - length + 1), 1000 + length, dtype=np.uint64)
        for j in range(length):
            out = out * U64(0x9E3779B97F4A7C15) + tokens[j : j + len(out)]
        yield 1000 + length, mix(out)


def _item_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(item_id, item tokens, hashes, kinds, places) of each test item with tokens."""
    for batch in batches:
        for i, tokens in token_hashes(batch.column("tokens")):
            if len(tokens):
                seeds = list(_seeds(tokens, [])) if len(tokens) >= SPAN else [x for x in _seeds(tokens, [len(tokens)]) if x[0] >= 1000]
                yield _seed_row(batch.column("item_id")[i], tokens, [(k, h, np.arange(len(h))) for k, h in seeds])


def _seed_row(key: pa.Scalar, tokens: np.ndarray, seeds: list[tuple[int, np.ndarray, np.ndarray]]) -> pa.RecordBatch:
    lists = [np.concatenate([h for _, h, _ in seeds]).view(np.int64), np.concatenate([np.full(len(h), k) for k, h, _ in seeds]), np.concatenate([p for _, _, p in seeds])]
    arrays = [pa.array([key.as_py()], pa.int64()), pa.array([tokens.tobytes()], pa.binary()), *[pa.array([x], pa.list_(pa.int64())) for x in lists]]
    return pa.RecordBatch.from_arrays(arrays, names=["id", "tokens", "hash", "kind", "place"])


_ROW = "id long, tokens binary, hash array<long>, kind array<long>, place array<long>"
_CHUNK = 1 << 16


def _bit_table(seeds: DataFrame) -> np.ndarray:
    """One bit for each hash modulo 2**``FILTER_BITS``: tables of the tasks, joined by pieces; its size is fixed."""

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = np.zeros(1 << FILTER_BITS, dtype=bool)
        for batch in batches:
            bits[(batch.column("hash").to_numpy().view(np.uint64) & U64((1 << FILTER_BITS) - 1)).astype(np.int64)] = True
        packed = np.packbits(bits).reshape(-1, min(_CHUNK, (1 << FILTER_BITS) // 8))
        for i in np.flatnonzero(packed.any(axis=1)):
            yield pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), pa.array([packed[i].tobytes()], pa.binary())], names=["piece", "bits"])

    def either(part: pa.Table) -> pa.Table:
        bits = np.bitwise_or.reduce([np.frombuffer(x.as_py(), dtype=np.uint8) for x in part.column("bits")])
        return pa.table([part.column("piece")[:1], pa.array([bits.tobytes()], pa.binary())], names=["piece", "bits"])

    schema = "piece int, bits binary"
    out = np.zeros((1 << FILTER_BITS) // 8, dtype=np.uint8).reshape(-1, min(_CHUNK, (1 << FILTER_BITS) // 8))
    for r in seeds.mapInArrow(mark, schema).groupBy("piece").applyInArrow(either, schema).collect():
        out[r["piece"]] = np.frombuffer(r["bits"], dtype=np.uint8)
    return out.ravel()


def _joined(rows: DataFrame, items: DataFrame, min_tokens: int, percent: int) -> DataFrame:
    """(id, item_id, ...) of the leaks in ``rows`` (id, tokens), both sides distributed."""
    spark = rows.sparkSession
    own = written(items.mapInArrow(_item_rows, _ROW).withColumn("item", F.monotonically_increasing_id()), "items")
    exploded = F.inline(F.arrays_zip("hash", "kind", "place"))
    test = own.select("item", exploded)
    short = sorted(r["kind"] - 1000 for r in test.where("kind >= 1000").select("kind").distinct().collect())  # below SPAN
    table = spark.sparkContext.broadcast(_bit_table(test.select("hash")))

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, tokens in token_hashes(batch.column("tokens")):
                hits = []
                for kind, h in _seeds(tokens, short):
                    at = (h & U64((1 << FILTER_BITS) - 1)).astype(np.int64)
                    place = np.flatnonzero(table.value[at >> 3] >> (7 - (at & 7)).astype(np.uint8) & 1)
                    hits.append((kind, h[place], place))
                if sum(len(p) for _, _, p in hits):
                    yield _seed_row(batch.column("id")[i], tokens, hits)

    docs = written(rows.select("id", "tokens").mapInArrow(read, _ROW).withColumn("row", F.monotonically_increasing_id()), "candidates")
    left = docs.select("row", exploded).withColumnRenamed("place", "at")
    met = left.join(test, ["hash", "kind"]).select("row", "item", (F.col("at") - F.col("place")).alias("shift")).distinct()
    pairs = written(met.groupBy("row", "item").agg(F.collect_list("shift").alias("shifts")), "meetings")
    both = pairs.join(docs.select("row", "id", F.col("tokens").alias("doc")), "row").join(own.select("item", F.col("id").alias("item_id"), F.col("tokens").alias("test")), "item")

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for key, item, doc, test, shifts in zip(*(batch.column(c) for c in ("id", "item_id", "doc", "test", "shifts")), strict=True):
                best = best_stretch(np.frombuffer(doc.as_py(), dtype=np.uint64), np.frombuffer(test.as_py(), dtype=np.uint64), sorted(shifts.as_py()), min_tokens, percent)
                if best:
                    out.append((key.as_py(), item.as_py(), *best))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], names=_FOUND)

    return both.select("id", "item_id", "doc", "test", "shifts").mapInArrow(verify, ", ".join(f"{c} long" for c in _FOUND))


_FOUND = ["id", "item_id", "doc_token", "item_token", "n_tokens", "n_agree"]


def leaks(docs: DataFrame, items: DataFrame, min_tokens: int = MIN_TOKENS, percent: int = PERCENT, block_hashes: int = 4 << 20) -> DataFrame:
    """doc_id, item_id, doc_token, item_token, n_tokens, n_agree: the best leak of each item in each document."""
    clean = _clean(items)
    picked = docs.select(F.col("doc_id").cast("long").alias("id"), token_column(F.col("text")).alias("tokens"))
    block = _block(clean, block_hashes)
    if block is None:
        return _joined(picked, clean, min_tokens, percent).withColumnRenamed("id", "doc_id")
    shared = docs.sparkSession.sparkContext.broadcast(block)

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column("id")
            rows = [(ids[i].as_py(), *hit) for i, doc in token_hashes(batch.column("tokens")) for hit in scan(doc, shared.value, min_tokens, percent)]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], names=_FOUND)

    return picked.mapInArrow(read, ", ".join(f"{c} long" for c in _FOUND)).withColumnRenamed("id", "doc_id")


def drop_leaks(docs: DataFrame, items: DataFrame, min_tokens: int = MIN_TOKENS, percent: int = PERCENT, block_hashes: int = 4 << 20) -> DataFrame:
    """The rows of ``docs`` that hold no leak; columns as they were."""
    tests = _clean(items)
    names = [f"_k{i}" for i in range(len(docs.columns))]
    text = names[[c.lower() for c in docs.columns].index("text")]
    keyed = docs.toDF(*names)
    block = _block(tests, block_hashes)
    if block is None:
        kept = written(keyed.withColumn("_row", F.monotonically_increasing_id()), "numbered")
        found = _joined(kept.select(F.col("_row").alias("id"), token_column(F.col(text)).alias("tokens")), tests, min_tokens, percent)
        return kept.join(found.select(F.col("id").alias("_row")).distinct(), "_row", "left_anti").drop("_row").toDF(*docs.columns)
    shared = docs.sparkSession.sparkContext.broadcast(block)

    @F.arrow_udf("boolean")
    def clean(tokens: pa.Array) -> pa.Array:
        return pa.array([not scan(doc, shared.value, min_tokens, percent) for _, doc in token_hashes(tokens)], pa.bool_())

    # only the tokens go to Python; the other columns wait in the JVM, in pages that can spill
    return keyed.where(clean(token_column(F.col(text)))).toDF(*docs.columns)
