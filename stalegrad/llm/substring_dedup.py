"""Repeated word windows found level by level, each level twice as long as the last.

Level one looks at windows of half the wanted length.  Of these a document only
names the ones that are the minimum of a window of the full length, which every
full-length window contains (so nothing is lost and about one window in thirteen
is named).  Names that occur in one document alone end there.  The survivors are
extended to the full length, and only full windows around a surviving name are
hashed (96 bits) and compared; ``repeat_levels`` goes on doubling until no
candidate is left, which measures how long repeats are.

A window is judged by the smallest doc_id in which it starts.  Texts with equal
word sequences are set aside first: all but those of the smallest id are wholly
covered if they reach the window length.

Edge cases: null and empty texts have no words; fewer words than a window are
never removed; rows without doc_id and rows that repeat an id do not count as
smaller than each other (rows without an id are left as they are and give no
windows); white space of a text is normalised in the digest only, as the kept
words are joined by one space.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stalegrad.llm.common import written
from stalegrad.llm.kernels import blocks, sliding_min, windows_hash, word_codes, word_spans

FEATURES = "doc_id long, n_words long, sha binary, names array<long>"


def _joined(data: np.ndarray, start: np.ndarray, end: np.ndarray, keep: np.ndarray | None = None) -> bytes:
    """The (kept) words joined by one space."""
    if keep is not None:
        start, end = start[keep], end[keep]
    if not len(start):
        return b""
    size = end - start + 1
    take = np.repeat(start - np.concatenate(([0], np.cumsum(size)[:-1])), size) + np.arange(size.sum())
    out = data[np.minimum(take, len(data) - 1)]
    out[np.cumsum(size) - 1] = 0x20
    return out[:-1].tobytes()


def _name_windows(codes: np.ndarray, window: int) -> np.ndarray:
    """For each window of the full length the minimum of its half-length hashes."""
    half = window // 2
    return sliding_min(windows_hash(codes, half), window - half + 1)


def features(docs: DataFrame, window: int) -> DataFrame:
    """Per row: word count, digest of the joined words, and the names of level one."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column("doc_id")
            for lo, hi, data, offs in blocks(batch.column("text")):
                start, end, first = word_spans(data, offs)
                codes = word_codes(data, start, end)
                counts, digests, names = [], [], []
                for r in range(hi - lo):
                    a, b = first[r], first[r + 1]
                    counts.append(b - a)
                    digests.append(hashlib.sha256(_joined(data, start[a:b], end[a:b])).digest())
                    m = _name_windows(codes[a:b], window)
                    names.append(np.unique(m).view(np.int64) if len(m) else None)
                yield pa.RecordBatch.from_arrays(
                    [ids[lo:hi], pa.array(counts, pa.int64()), pa.array(digests, pa.binary()), pa.array(names, pa.list_(pa.int64()))],
                    names=["doc_id", "n_words", "sha", "names"],
                )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(read, FEATURES)


def _texts(batch: pa.RecordBatch) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, list[tuple[int, int, int]]]]:
    """Blocks with their words and (row, first word, end word) of the rows whose digest is the wanted one."""
    shas = batch.column("sha")
    for lo, hi, data, offs in blocks(batch.column("text")):
        start, end, first = word_spans(data, offs)
        rows = []
        for r in range(hi - lo):
            a, b = first[r], first[r + 1]
            if hashlib.sha256(_joined(data, start[a:b], end[a:b])).digest() == shas[lo + r].as_py():
                rows.append((lo + r, a, b))  # else another text under the same id
        yield data, start, end, rows


def windows(texts: DataFrame, window: int) -> DataFrame:
    """Rows (h1, h2, doc_id, variant, pos) of the full windows around surviving names."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for data, start, end, rows in _texts(batch):
                codes, second = word_codes(data, start, end), word_codes(data, start, end, lane=1)
                h1, h2, doc, variant, place = [], [], [], [], []
                for i, a, b in rows:
                    if b - a < window:
                        continue
                    alive = np.sort(np.asarray(batch.column("names")[i].values, dtype=np.int64).view(np.uint64))
                    m = _name_windows(codes[a:b], window)
                    pos = np.flatnonzero(alive[np.minimum(np.searchsorted(alive, m), len(alive) - 1)] == m)
                    h1.append(windows_hash(codes[a:b], window)[pos])
                    h2.append(windows_hash(second[a:b], window, 1)[pos])
                    doc.append(np.full(len(pos), batch.column("doc_id")[i].as_py()))
                    variant.append(np.full(len(pos), batch.column("variant")[i].as_py(), dtype=np.int32))
                    place.append(pos.astype(np.int32))
                if h1:
                    low = (np.concatenate(h2) & np.uint64(0xFFFFFFFF)).astype(np.uint32).view(np.int32)
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(np.concatenate(h1).view(np.int64)), pa.array(low), pa.array(np.concatenate(doc)), pa.array(np.concatenate(variant)), pa.array(np.concatenate(place))],
                        names=["h1", "h2", "doc_id", "variant", "pos"],
                    )

    return texts.select("doc_id", "sha", "variant", "names", "text").mapInArrow(read, "h1 long, h2 int, doc_id long, variant int, pos int")


def _survivors(feats: DataFrame) -> DataFrame:
    """(doc_id, sha, variant, names): names of level one that start in two documents or more."""
    named = feats.select("doc_id", "variant", F.explode("names").alias("name"))
    shared = written(named.groupBy("name").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).where("lo < hi").select("name"), "shared")
    kept = named.join(shared, "name").groupBy("doc_id", "variant").agg(F.collect_list("name").alias("names"))
    return feats.select("doc_id", "sha", "variant").join(kept, ["doc_id", "variant"])


def _with_variant(feats: DataFrame) -> DataFrame:
    """Adds ``variant``: 0 but for the further texts of an id that was given to several."""
    least = feats.groupBy("doc_id").agg(F.min("sha").alias("_least"))
    return feats.join(least, "doc_id").withColumn("variant", F.when(F.col("sha") == F.col("_least"), 0).otherwise(F.hash("sha"))).drop("_least")


def remove_repeats(docs: DataFrame, window: int = 50) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256, and kept_text where words went (else null)."""
    light = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    feats = written(features(docs, window), "windows")
    long_enough = feats.where((F.col("n_words") >= window) & F.col("doc_id").isNotNull())
    firsts = written(long_enough.groupBy("sha").agg(F.min("doc_id").alias("first_id")), "firsts")
    sole = _with_variant(long_enough.join(firsts, "sha").where(F.col("doc_id") == F.col("first_id")).dropDuplicates(["doc_id", "sha"]))
    alive = _survivors(sole)
    found = windows(light.join(alive, "doc_id"), window)
    # written, so that the join below meets two plain shuffles and can split a hot window
    smallest = written(found.groupBy("h1", "h2").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).where("lo < hi").select("h1", "h2", "lo"), "smallest")
    covered = found.join(smallest, ["h1", "h2"]).where("doc_id > lo").groupBy("doc_id", "variant").agg(F.collect_set("pos").alias("starts"))
    marked = alive.select("doc_id", "sha", "variant").join(covered, ["doc_id", "variant"]).drop("variant")
    cut = _cut(light.join(marked, "doc_id").select("doc_id", "sha", "starts", "text"), window).dropDuplicates(["doc_id", "sha"])
    whole = (F.col("doc_id") > F.col("first_id")) & F.col("first_id").isNotNull()
    out = feats.select("doc_id", "n_words", "sha").join(firsts, "sha", "left").join(cut, ["doc_id", "sha"], "left")
    empty = hashlib.sha256(b"").hexdigest()
    return out.select(
        "doc_id",
        "n_words",
        F.when(whole, F.col("n_words")).otherwise(F.coalesce("cut_words", F.lit(0))).cast("long").alias("n_removed"),
        F.when(whole, F.lit(empty)).otherwise(F.coalesce("cut_sha256", F.lower(F.hex("sha")))).alias("kept_sha256"),
        F.when(whole, F.lit("")).otherwise(F.col("cut_text")).alias("kept_text"),
    )


def _cut(texts: DataFrame, window: int) -> DataFrame:
    """Removes the words under the given window starts."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for data, start, end, rows in _texts(batch):
                out = []
                for i, a, b in rows:
                    depth = np.zeros(b - a + 1, dtype=np.int64)
                    pos = np.asarray(batch.column("starts")[i].values, dtype=np.int64)
                    np.add.at(depth, pos, 1)
                    np.add.at(depth, pos + window, -1)
                    keep = np.cumsum(depth[:-1]) == 0
                    text = _joined(data, start[a:b], end[a:b], keep)
                    out.append((batch.column("doc_id")[i].as_py(), batch.column("sha")[i].as_py(), int((~keep).sum()), hashlib.sha256(text).hexdigest(), text.decode()))
                if out:
                    kinds = (pa.int64(), pa.binary(), pa.int64(), pa.string(), pa.string())
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], names=["doc_id", "sha", "cut_words", "cut_sha256", "cut_text"])

    return texts.mapInArrow(read, "doc_id long, sha binary, cut_words long, cut_sha256 string, cut_text string")


def repeat_levels(docs: DataFrame, first_window: int = 50) -> DataFrame:
    """window_words, windows, documents: what repeats across documents at each doubled length.

    Runs until no candidate survives; a document stays a candidate for twice the
    length only while it holds repeats of the length before.
    """
    spark = docs.sparkSession
    window, alive, rows = first_window, docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where("doc_id IS NOT NULL"), []
    while True:
        feats = _with_variant(features(alive, window).where(F.col("n_words") >= window))
        found = windows(alive.join(_survivors(feats), "doc_id"), window)
        shared = found.groupBy("h1", "h2").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).where("lo < hi")
        hits = written(found.join(shared, ["h1", "h2"]).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")), "level")
        total = hits.agg(F.sum("n"), F.count(F.lit(1))).first()
        if not total[1]:
            return spark.createDataFrame(rows, "window_words long, windows long, documents long")
        rows.append((window, int(total[0]), int(total[1])))
        alive, window = alive.join(hits.select("doc_id"), "doc_id", "left_semi"), window * 2
