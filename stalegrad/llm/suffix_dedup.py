"""Byte strings that start twice anywhere, found by suffix order over a prefix-free parse.

Every window of ``width`` bytes has a name: the least hash among its ``GRAM``-byte
substrings.  Equal windows have equal names, and neighbours mostly share theirs,
so a text falls into segments of one name (about 150 window starts each).  Names
that occur once in the corpus end there.  The other segments are gathered by
name, equal ones once with their number, and within each small part of the
names the suffix order of its segments (``prefix_free``) shows which windows
have a twin.  As equal windows always meet in one part, the parts together give
what one suffix array of the corpus would.

A name whose distinct segments are more than ``part_bytes`` long together is not
put into one task: its windows are compared by 128-bit fingerprints spread over
all tasks.  Equal texts count as two occurrences of each window they hold.

Edge cases: null is the empty text; texts shorter than ``width`` are kept; ids do
not matter for the removal (null and repeated ids are rows like others); removal
may cut inside a UTF-8 character, so kept bytes are binary.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stalegrad.llm.common import written
from stalegrad.llm.kernels import BLOCK_BYTES, U64, blocks, byte_codes, sliding_min, windows_hash
from stalegrad.llm.prefix_free import repeated_starts

GRAM = 100
PART_BYTES = 512 << 10
SEGMENT = ["name", "dig", "content", "weight", "sha", "start"]


def _names(codes: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the grams of a text and the name of each window."""
    gram = min(GRAM, width)
    hashes = windows_hash(codes, gram)
    return hashes, sliding_min(hashes, width - gram + 1)


def _runs(names: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    begin = np.flatnonzero(np.concatenate((np.ones(min(1, len(names)), dtype=bool), names[1:] != names[:-1])))
    return begin, np.append(begin[1:], len(names)) - begin


def _rows(batch: pa.RecordBatch, column: str = "text") -> Iterator[tuple[int, np.ndarray]]:
    for lo, hi, data, offs in blocks(batch.column(column)):
        for r in range(hi - lo):
            yield lo + r, data[offs[r] : offs[r + 1]]


def name_rows(texts: DataFrame, width: int) -> DataFrame:
    """(sha, name, seen): names of a text and how often their gram stands there (2: twice or more)."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            whose, names, seen = [], [], []
            for i, data in _rows(batch):
                if len(data) < width:
                    continue
                hashes, named = _names(byte_codes(0)[data], width)
                own = np.unique(named)
                at = np.minimum(np.searchsorted(own, hashes), len(own) - 1)
                count = np.bincount(at[own[at] == hashes], minlength=len(own))
                whose.append(np.full(len(own), i))
                names.append(own)
                seen.append(np.minimum(count, 2))
            if whose:
                yield pa.RecordBatch.from_arrays(
                    [batch.column("sha").take(pa.array(np.concatenate(whose))), pa.array(np.concatenate(names).view(np.int64)), pa.array(np.concatenate(seen).astype(np.int32))],
                    names=["sha", "name", "seen"],
                )

    return texts.select("sha", "text").mapInArrow(read, "sha binary, name long, seen int")


def segments(texts: DataFrame, width: int) -> DataFrame:
    """(name, dig, content, weight, sha, start): segments of surviving names; dig stands for name and content."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = (pa.int64(), pa.binary(), pa.binary(), pa.int64(), pa.binary(), pa.int64())
        for batch in batches:
            out: list[tuple[int, bytes, bytes, int, bytes, int]] = []
            held = 0
            for i, data in _rows(batch):
                alive = np.sort(np.asarray(batch.column("names")[i].values, dtype=np.int64).view(np.uint64))
                _, named = _names(byte_codes(0)[data], width)
                begin, size = _runs(named)
                own = named[begin]
                hit = np.flatnonzero(alive[np.minimum(np.searchsorted(alive, own), len(alive) - 1)] == own)
                raw, weight, sha = data.tobytes(), batch.column("weight")[i].as_py(), batch.column("sha")[i].as_py()
                for k in hit.tolist():
                    at = int(begin[k])
                    content = raw[at : at + int(size[k]) + width - 1]
                    out.append((int(own[k : k + 1].view(np.int64)[0]), hashlib.blake2b(content, digest_size=16, key=own[k].tobytes()).digest(), content, weight, sha, at))
                    held += len(content)
                if held > BLOCK_BYTES:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], names=SEGMENT)
                    out, held = [], 0
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], names=SEGMENT)

    return texts.select("sha", "text", "weight", "names").mapInArrow(read, "name long, dig binary, content binary, weight long, sha binary, start long")


def _masked(mask: np.ndarray) -> bytes:
    return np.packbits(mask).tobytes()


def _mark(width: int):
    """A part's segments -> (dig, mask) with a bit for each window start that has a twin."""

    def mark(part: pa.Table) -> pa.Table:
        part = part.sort_by("name")
        names = part.column("name").to_numpy()
        lengths = np.fromiter((len(c.as_py()) for c in part.column("content")), dtype=np.int64, count=len(names))
        copies, digs = part.column("copies").to_numpy(), part.column("dig")
        group = np.flatnonzero(np.concatenate(([True], names[1:] != names[:-1]))) if len(names) else np.zeros(0, np.int64)
        size = np.concatenate(([0], np.cumsum(lengths)))
        out_dig, out_mask = [], []
        at = 0
        while at < len(group):  # several whole names at a time, about a block of bytes
            stop = max(at + 1, int(np.searchsorted(size[group], size[group[at]] + BLOCK_BYTES)))
            lo, hi = group[at], group[stop] if stop < len(group) else len(names)
            data = np.frombuffer(b"".join(c.as_py() for c in part.column("content")[lo:hi]), dtype=np.uint8)
            offs = size[lo : hi + 1] - size[lo]
            twin = repeated_starts(data, offs, width)
            for k in range(hi - lo):
                mask = twin[offs[k] : offs[k + 1] - width + 1] | (copies[lo + k] > 1)
                if mask.any():
                    out_dig.append(digs[lo + k].as_py())
                    out_mask.append(_masked(mask))
            at = stop
        return pa.table([pa.array(out_dig, pa.binary()), pa.array(out_mask, pa.binary())], names=["dig", "mask"])

    return mark


def _fingerprints(distinct: DataFrame, width: int) -> DataFrame:
    """(h1, h2, dig, pos, copies) for every window of the given segments."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, data in _rows(batch, "content"):
                h1, h2 = windows_hash(byte_codes(0)[data], width), windows_hash(byte_codes(1)[data], width, 1)
                n = len(h1)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(h1.view(np.int64)), pa.array(h2.view(np.int64)), pa.array([batch.column("dig")[i].as_py()] * n, pa.binary()), pa.array(np.arange(n)), pa.array([batch.column("copies")[i].as_py()] * n, pa.int64())],
                    names=["h1", "h2", "dig", "pos", "copies"],
                )

    return distinct.select("dig", "content", "copies").mapInArrow(read, "h1 long, h2 long, dig binary, pos long, copies long")


def _bits(rows: DataFrame) -> DataFrame:
    """(dig, pos) rows -> (dig, mask)."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            masks = []
            for p in batch.column("places"):
                at = np.asarray(p.values)
                mask = np.zeros(at.max() + 1, dtype=bool)
                mask[at] = True
                masks.append(_masked(mask))
            yield pa.RecordBatch.from_arrays([batch.column("dig"), pa.array(masks, pa.binary())], names=["dig", "mask"])

    return rows.groupBy("dig").agg(F.collect_set("pos").alias("places")).mapInArrow(read, "dig binary, mask binary")


def _cut(texts: DataFrame, width: int) -> DataFrame:
    """(sha, cut_bytes, cut_spans, cut_sha256, kept_bytes) of texts with marked starts."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for i, data in _rows(batch):
                depth = np.zeros(len(data) + 1, dtype=np.int32)
                marks = batch.column("marks")[i].values
                for start, mask in zip(marks.field("start").to_pylist(), marks.field("mask").to_pylist(), strict=True):
                    at = start + np.flatnonzero(np.unpackbits(np.frombuffer(mask, dtype=np.uint8)))
                    depth[at] += 1
                    depth[at + width] -= 1
                gone = np.cumsum(depth[:-1]) > 0
                kept = data[~gone].tobytes()
                spans = int(gone[0]) + int((gone[1:] & ~gone[:-1]).sum()) if len(gone) else 0
                out.append((batch.column("sha")[i].as_py(), int(gone.sum()), spans, hashlib.sha256(kept).hexdigest(), kept))
            if out:
                kinds = (pa.binary(), pa.int64(), pa.int64(), pa.string(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], names=["sha", "cut_bytes", "cut_spans", "cut_sha256", "kept_bytes"])

    return texts.select("sha", "text", "marks").mapInArrow(read, "sha binary, cut_bytes long, cut_spans long, cut_sha256 string, kept_bytes binary")


def remove_repeats(docs: DataFrame, width: int = 400, part_bytes: int = PART_BYTES) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, and kept_bytes where bytes went (else null)."""
    text = F.coalesce(F.col("text"), F.lit(""))
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"), F.unhex(F.sha2(text, 256)).alias("sha"))
    sized = base.select("doc_id", "sha", F.octet_length("text").cast("long").alias("n_bytes"))
    row_id = F.coalesce("doc_id", F.xxhash64("sha"))
    groups = written(sized.where(F.col("n_bytes") >= width).groupBy("sha").agg(F.min(row_id).alias("rid"), F.count(F.lit(1)).alias("copies")), "texts")
    weight = F.least("copies", F.lit(2)).cast("long")

    keyed = base.where(F.octet_length("text") >= width).withColumn("rid", row_id).select("rid", "sha", "text")
    seen = name_rows(keyed, width)  # every copy of a text counts, as it should
    alive = written(seen, "names")
    shared = written(alive.groupBy("name").agg(F.sum("seen").alias("n")).where("n > 1").select("name"), "shared")
    named = alive.select("sha", "name").join(shared, "name").groupBy("sha").agg(F.collect_set("name").alias("names"))
    chosen = groups.join(named, "sha").select("rid", "sha", weight.alias("weight"), "names")

    def with_text(rows: DataFrame) -> DataFrame:
        """One row for each text: the first copy's, met on its row id."""
        return keyed.join(rows.withColumnRenamed("sha", "_sha"), "rid").where("sha = _sha").drop("_sha").dropDuplicates(["rid", "sha"])

    cut = segments(with_text(chosen), width)
    distinct = written(cut.groupBy("name", "dig", "content").agg(F.sum("weight").alias("copies")), "segments")
    load = distinct.groupBy("name").agg(F.sum(F.length("content")).alias("bytes"))
    total = distinct.agg(F.sum(F.length("content"))).first()[0] or 0
    parts = int(total // part_bytes) + 1
    sized_names = distinct.join(load, "name")
    light = sized_names.where(F.col("bytes") <= part_bytes).withColumn("part", F.pmod(F.xxhash64("name"), F.lit(parts)))
    masks = light.select("part", "name", "dig", "content", "copies").groupBy("part").applyInArrow(_mark(width), "dig binary, mask binary")
    prints = _fingerprints(sized_names.where(F.col("bytes") > part_bytes), width)
    # written, so that the join meets two plain shuffles and can split a hot window
    twice = written(prints.groupBy("h1", "h2").agg(F.sum("copies").alias("n")).where("n > 1").select("h1", "h2"), "twice")
    heavy = _bits(prints.join(twice, ["h1", "h2"]).select("dig", "pos"))
    masks = written(masks.unionByName(heavy), "masks")

    marks = cut.select("dig", "sha", "start").join(masks, "dig").groupBy("sha").agg(F.collect_list(F.struct("start", "mask")).alias("marks"))
    lone = groups.where("copies = 1").join(marks, "sha").select("rid", "sha", "marks")
    done = _cut(with_text(lone), width)

    out = sized.join(groups.select("sha", "copies"), "sha", "left").join(done, "sha", "left")
    whole = F.coalesce(F.col("copies") > 1, F.lit(False))
    empty = hashlib.sha256(b"").hexdigest()
    return out.select(
        "doc_id",
        "n_bytes",
        F.when(whole, F.col("n_bytes")).otherwise(F.coalesce("cut_bytes", F.lit(0))).cast("long").alias("n_removed"),
        F.when(whole, F.lit(1)).otherwise(F.coalesce("cut_spans", F.lit(0))).cast("long").alias("n_spans"),
        F.when(whole, F.lit(empty)).otherwise(F.coalesce("cut_sha256", F.lower(F.hex("sha")))).alias("kept_sha256"),
        F.when(whole, F.lit(b"")).otherwise(F.col("kept_bytes")).alias("kept_bytes"),
    )
