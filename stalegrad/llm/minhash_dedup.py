"""Near duplicates by circulant MinHash, banding and exact Jaccard.

Two permutations of a fixed universe of 2**22 places make all coordinates of a
signature: the first scatters the shingles, the second is read at places shifted
circularly by 0, 1, 2, ...  (Texts of many million distinct shingles fill that
universe; they then meet more candidates, which the exact check sorts out.)  Doubling the second permutation once turns the K values of a
shingle into K neighbours in memory, so a signature is a minimum over rows of
one sliding view.

Bands of the signature retrieve candidates; two documents are linked only if the
Jaccard similarity of the two full shingle sets (64-bit fingerprints of the
words) reaches the threshold, in integers.  With ``bands`` bands of ``rows``
rows a pair at the threshold t is missed with probability (1 - t**rows)**bands:
4e-9 for t = 0.85 with 7 rows, 2e-9 for t = 0.8 with 5 rows.

Equal sets are one class from the start, however many rows share them.  In each
band bucket all sets are first compared with the one of the smallest id, which
joins most groups at the cost of a star.  A bucket whose sets then still lie in
several components is compared wholly, but inside tasks: its sets are dealt into
blocks of bounded bytes and sets, each pair of blocks meets in one task, and only links
that join two components leave it.  Buckets with the same members are compared
once.  So no link between different sets is lost, and no pair that is not a link
ever becomes a row.

Edge cases: null or wordless texts have the empty set and are linked with
nothing; fewer words than a shingle form one shingle; rows that repeat an id are
one vertex; rows without an id are left alone (component null, kept).
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stalegrad.llm.common import fresh, written
from stalegrad.llm.kernels import LOWER, U64, blocks, mix, word_codes, word_spans

UNIVERSE_BITS = 22
BANDS = 50
BLOCK = 1 << 20
BLOCK_SETS = 1 << 10


#: Odd multipliers of the two permutations.
SCATTER, SHIFTED = (0x9E3779B1, 0x85EBCA6B, 0xC2B2AE35), (0x27D4EB2F, 0x165667B1, 0xD3A2646D)


def permuted(x: np.ndarray, multipliers: tuple[int, ...]) -> np.ndarray:
    """A permutation of 0 .. 2**UNIVERSE_BITS - 1: each round multiplies by an odd number and folds the upper half down."""
    mask = np.uint32((1 << UNIVERSE_BITS) - 1)
    x = x.astype(np.uint32) & mask
    for m in multipliers:
        x = (x * np.uint32(m)) & mask
        x ^= x >> np.uint32(UNIVERSE_BITS // 2)
    return x


@lru_cache(maxsize=1)
def shifted_rows(width: int) -> np.ndarray:
    """A view whose row x holds the second permutation at x, x+1, ... (circularly)."""
    size, piece = 1 << UNIVERSE_BITS, 1 << 16
    second = np.empty(size + width - 1, dtype=np.uint32)
    for lo in range(0, size, piece):  # piecewise, as a worker has little room beside the table
        second[lo : min(lo + piece, size)] = permuted(np.arange(lo, min(lo + piece, size), dtype=np.uint32), SHIFTED)
    second[size:] = second[: width - 1]
    return np.lib.stride_tricks.sliding_window_view(second, width)


def shingle_set(codes: np.ndarray, size: int) -> np.ndarray:
    """Sorted distinct fingerprints of the word shingles of one text."""
    n = len(codes)
    if not n:
        return np.zeros(0, dtype=np.uint64)
    size = min(size, n)
    out = np.zeros(n - size + 1, dtype=np.uint64)
    for j in range(size):
        out = out * U64(0x9E3779B97F4A7C15) + codes[j : n - size + 1 + j]
    return np.unique(mix(out + U64(size)))


def signature(shingles: np.ndarray, width: int) -> np.ndarray:
    rows = shifted_rows(width)
    at = permuted(shingles & U64((1 << UNIVERSE_BITS) - 1), SCATTER)
    best = rows[at[:4096]].min(axis=0)
    for i in range(4096, len(at), 4096):
        best = np.minimum(best, rows[at[i : i + 4096]].min(axis=0))
    return best


def band_keys(shingles: np.ndarray, bands: int, rows: int) -> np.ndarray:
    grid = signature(shingles, bands * rows).reshape(bands, rows).astype(np.uint64)
    key = np.arange(1, bands + 1, dtype=np.uint64)
    for j in range(rows):
        key = mix(key * U64(0x9E3779B97F4A7C15) + grid[:, j])
    return key.view(np.int64)


def _sets(column: pa.Array, size: int) -> Iterator[tuple[int, np.ndarray]]:
    for lo, hi, data, offs in blocks(column):
        lower = LOWER[data]
        start, end, first = word_spans(lower, offs)
        codes = word_codes(lower, start, end)
        for r in range(hi - lo):
            yield lo + r, shingle_set(codes[first[r] : first[r + 1]], size)


def rows_for(percent: int, bands: int = BANDS) -> int:
    """Rows a band: as many as leave a pair at the threshold unseen with 1e-8 at most, up to 7 (from 85 percent) or 5."""
    for rows in range(7 if percent >= 85 else 5, 0, -1):
        if (1 - (percent / 100) ** rows) ** bands <= 1e-8:
            return rows
    raise ValueError(f"{bands} bands cannot serve a threshold of {percent} percent")


def features(docs: DataFrame, size: int, bands: int, rows: int) -> DataFrame:
    """doc_id, n_shingles, set_key (digest of the set, null if empty), bands."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            count, key, band = [], [], []
            for _, s in _sets(batch.column("text"), size):
                count.append(len(s))
                key.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None)
                band.append(band_keys(s, bands, rows) if len(s) else None)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(count, pa.int64()), pa.array(key, pa.binary()), pa.array(band, pa.list_(pa.int64()))], names=["doc_id", "n_shingles", "set_key", "bands"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(read, "doc_id long, n_shingles long, set_key binary, bands array<long>")


def _shingles(docs: DataFrame, size: int) -> DataFrame:
    """set_key, shingles: the full sets of the given rows (set_key, text)."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, s in _sets(batch.column("text"), size):
                own = hashlib.blake2b(s.tobytes(), digest_size=16).digest()
                if own == batch.column("set_key")[i].as_py():
                    yield pa.RecordBatch.from_arrays([pa.array([own], pa.binary()), pa.array([s.tobytes()], pa.binary())], names=["set_key", "shingles"])

    return docs.mapInArrow(read, "set_key binary, shingles binary")


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b, ka, kb) whose sets reach the threshold: 100 * both >= percent * any."""

    def test(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column("sa"), batch.column("sb"), strict=True):
                x, y = np.frombuffer(x.as_py(), dtype=np.uint64), np.frombuffer(y.as_py(), dtype=np.uint64)
                both = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(100 * both >= percent * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b")], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))

    left = sets.select(F.col("set_key").alias("ka"), F.col("shingles").alias("sa"))
    right = sets.select(F.col("set_key").alias("kb"), F.col("shingles").alias("sb"))
    return pairs.join(left, "ka").join(right, "kb").select("a", "b", "sa", "sb").mapInArrow(test, "a long, b long")


def _linked(both: np.ndarray, sizes: np.ndarray, who: np.ndarray, side: np.ndarray | None, percent: int) -> Iterator[tuple[int, int]]:
    """Pairs i < j of different components and sides whose overlap ``both`` reaches the threshold, by strips of rows."""
    for lo in range(0, len(sizes), 128):
        strip = slice(lo, lo + 128)
        linked = 100 * both[strip] >= percent * (sizes[strip, None] + sizes[None] - both[strip])
        linked &= who[strip, None] != who[None]
        if side is not None:
            linked &= side[strip, None] != side[None]
        for i, j in zip(*np.nonzero(np.triu(linked, lo + 1)), strict=True):
            yield lo + i, j


def _inside(sets: list[np.ndarray], side: np.ndarray, component: list[int], percent: int) -> list[tuple[int, int]]:
    """Links between components among the sets of one task: enough of them to join what is linked.

    ``side`` is 0 and 1 for the two blocks that meet here (all 0 for one block);
    pairs within a block are another task's if there are two.
    """
    sizes = np.fromiter(map(len, sets), dtype=np.int64, count=len(sets))
    up: dict[int, int] = {}

    def root(c: int) -> int:
        while up.get(c, c) != c:
            c = up[c]
        return c

    out, both, two = [], None, bool(side.any())
    if len(sets) > 12:  # all overlaps at once, over the shingles that two sets or more have
        flat = np.concatenate(sets)
        _, which, count = np.unique(flat, return_inverse=True, return_counts=True)
        column = np.where(count > 1, np.cumsum(count > 1) - 1, -1)[which]
        row = np.repeat(np.arange(len(sets)), sizes)
        both = np.zeros((len(sets), len(sets)), dtype=np.float32)
        for lo in range(0, int(column.max()) + 1, 1024):
            here = (column >= lo) & (column < lo + 1024)
            grid = np.zeros((len(sets), 1024), dtype=np.float32)
            grid[row[here], column[here] - lo] = 1
            both += grid @ grid.T
        pairs = _linked(both, sizes, np.array(component), side if two else None, percent)
    else:
        pairs = ((i, j) for i in range(len(sets)) for j in range(i + 1, len(sets)))
    for i, j in pairs:
        if two and side[i] == side[j]:
            continue
        a, b = root(component[i]), root(component[j])
        if a == b or 100 * min(sizes[i], sizes[j]) < percent * max(sizes[i], sizes[j]):
            continue
        if both is None:
            shared = len(np.intersect1d(sets[i], sets[j], assume_unique=True))
            if 100 * shared < percent * (sizes[i] + sizes[j] - shared):
                continue
        up[max(a, b)] = min(a, b)
        out.append((int(i), int(j)))
    return out


def _compared(members: DataFrame, sets: DataFrame, percent: int, block: int) -> DataFrame:
    """Links (a, b) between components within each bucket of ``members``, all pairs considered.

    Members are dealt into ``blocks`` by hash; block x goes to each task (x, y).
    """
    own = F.pmod(F.xxhash64("set_key", "bucket"), F.col("blocks")).cast("int")
    spread = members.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    placed = spread.select("bucket", "rep", "set_key", "component", F.least("own", "other").alias("x"), F.greatest("own", "other").alias("y"), (F.col("own") != F.least("own", "other")).cast("int").alias("side"))
    total = members.agg(F.sum(F.col("n") * 8 * F.col("blocks"))).first()[0] or 0
    parts = int(total // block) + 1

    def meet(part: pa.Table) -> pa.Table:
        part = part.sort_by([("bucket", "ascending"), ("x", "ascending"), ("y", "ascending")])
        bucket, x, y, side = (part.column(c).to_numpy() for c in ("bucket", "x", "y", "side"))
        rep, component, data = part.column("rep").to_pylist(), part.column("component").to_pylist(), part.column("shingles")
        edge = np.flatnonzero((bucket[1:] != bucket[:-1]) | (x[1:] != x[:-1]) | (y[1:] != y[:-1])) + 1
        a, b = [], []
        for lo, hi in zip([0, *edge.tolist()], [*edge.tolist(), len(bucket)], strict=True):
            group = [np.frombuffer(v.as_py(), dtype=np.uint64) for v in data[lo:hi]]
            for i, j in _inside(group, side[lo:hi], component[lo:hi], percent):
                a.append(rep[lo + i])
                b.append(rep[lo + j])
        return pa.table([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    keyed = placed.withColumn("part", F.pmod(F.xxhash64("bucket", "x", "y"), F.lit(parts))).join(sets, "set_key")
    return keyed.groupBy("part").applyInArrow(meet, "a long, b long")


def components(edges: DataFrame) -> DataFrame:
    """(id, component): the least vertex reachable, for every vertex of ``edges`` (a, b).

    Least neighbour's label, then the label's label, until nothing changes; each
    round is written, so lineage stays short and hubs are pre-aggregated.
    """
    both = written(edges.select(F.col("a").alias("id"), F.col("b").alias("to")).unionByName(edges.select(F.col("b").alias("id"), F.col("a").alias("to"))).distinct(), "edges")
    labels = written(both.groupBy("id").agg(F.least(F.col("id"), F.min("to")).alias("component")), "labels")
    while True:
        offers = both.join(labels.withColumnsRenamed({"id": "to", "component": "offer"}), "to").groupBy("id").agg(F.min("offer").alias("offer"))
        lower = labels.join(offers, "id").select("id", F.least("component", "offer").alias("next"), "component")
        jump = labels.select(F.col("id").alias("next"), F.col("component").alias("jumped"))
        labels = written(lower.join(jump, "next").select("id", F.least("jumped", "next").alias("component"), (F.least("jumped", "next") < F.col("component")).alias("moved")), "labels")
        moved = labels.where("moved").limit(1).count()
        labels = labels.select("id", "component")
        if not moved:
            return labels


def near_duplicates(docs: DataFrame, size: int = 5, percent: int = 80, bands: int = BANDS, rows: int | None = None, block: int = BLOCK) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row of ``docs``."""
    feats = written(features(docs, size, bands, rows or rows_for(percent, bands)), "minhash")
    full = feats.where("set_key IS NOT NULL AND doc_id IS NOT NULL")
    # aggregates that a join meets are written first: two plain shuffles let it split a hot key
    classes = written(full.groupBy("set_key").agg(F.min("doc_id").alias("rep")), "classes")
    reps = full.join(classes, "set_key").where("doc_id = rep").select("set_key", "rep", "n_shingles", "bands").dropDuplicates(["set_key"])

    exploded = reps.select("rep", "set_key", F.col("n_shingles").alias("n"), F.explode("bands").alias("bucket"))
    heads = exploded.groupBy("bucket").agg(F.min(F.struct("rep", "set_key", "n")).alias("head"), F.count(F.lit(1)).alias("m")).where("m > 1")
    members = written(exploded.join(written(heads.select("bucket", "head"), "heads"), "bucket"), "buckets")

    def fits(n: str, m: str):  # Jaccard is at most the ratio of the sizes
        return 100 * F.least(n, m) >= percent * F.greatest(n, m)

    stars = members.where(F.col("head.set_key") != F.col("set_key")).where(fits("n", "head.n"))
    stars = stars.select(F.col("head.rep").alias("a"), F.col("rep").alias("b"), F.col("head.set_key").alias("ka"), F.col("set_key").alias("kb")).distinct()

    multi = members.select("set_key", F.col("rep").alias("doc_id")).distinct()
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(multi, "doc_id").select("set_key", "text")
    sets = written(_shingles(texts, size).dropDuplicates(["set_key"]), "sets")
    links = written(_verified(stars, sets, percent), "links")
    # an id that was given to several sets joins their classes
    owners = full.join(classes, "set_key").select("doc_id", "rep")
    shared = owners.groupBy("doc_id").agg(F.min("rep").alias("a"), F.max("rep").alias("_hi")).where("a < _hi").select("doc_id", "a")
    same = owners.join(shared, "doc_id").where("a < rep").select("a", F.col("rep").alias("b"))
    first = components(links)

    owned = members.join(first.withColumnRenamed("id", "rep"), "rep", "left").select("bucket", "rep", "set_key", "n", F.coalesce("component", "rep").alias("component"))
    open_ = owned.groupBy("bucket").agg(F.min("component").alias("lo"), F.max("component").alias("hi"), F.count(F.lit(1)).alias("m"), F.sum(F.xxhash64("set_key").cast("decimal(38,0)")).alias("who"), F.sum("n").alias("load")).where("lo < hi")
    once = open_.groupBy("m", "who", "load", "lo", "hi").agg(F.min("bucket").alias("bucket"))  # equal members: one bucket stands for all
    pieces = F.greatest(F.ceil(F.col("load") * 8 / block), F.ceil(F.col("m") / BLOCK_SETS)).cast("int")  # bytes and sets a block are bounded
    dealt = once.select("bucket", pieces.alias("blocks"), (F.col("load") * 8).alias("bytes"))
    more = _compared(written(owned.join(written(dealt, "dealt"), "bucket"), "open"), sets, percent, block)

    final = components(links.unionByName(more).unionByName(same))
    labelled = feats.join(classes, "set_key", "left").join(final.withColumnRenamed("id", "rep"), "rep", "left")
    component = F.coalesce("component", "rep", "doc_id")
    component = F.when(F.col("doc_id").isNotNull(), component)
    return labelled.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def drop_near(docs: DataFrame, size: int = 5, percent: int = 80) -> DataFrame:
    """The rows of ``docs`` with one document of each component, the smallest doc_id.

    Rows that repeat an id stay together; exact copies are another operator's work.
    """
    name = fresh(docs, "_gone")
    gone = near_duplicates(docs, size, percent).where("NOT kept").select(F.col("doc_id").alias(name)).distinct()
    return docs.join(gone, F.col("doc_id").cast("long") == F.col(name), "left_anti")
