"""Exact duplicates through a cuckoo-filter index of live digests.

The digest space is dealt into shards of about ``SHARD_KEYS`` rows at most.  Each
shard owns one cuckoo filter (four 16-bit fingerprints a bucket, two candidate
buckets a key) and, beside it, the stored keys by bucket.  A lookup that the
filter denies is new without touching the keys; a filter hit is verified against
the stored keys of its bucket, and only a verified hit folds a row into the group
that is there.  When an insertion runs out of evictions the filter doubles and is
rebuilt from the stored keys, so no key is ever lost.  Deletion takes a live
count down and removes the fingerprint with the last copy.

Rows reach their shard combined within each Arrow batch only (so that a group
with a third of all rows costs one row a batch); whether two rows are the same
group is the filter's decision.  Digests are SHA-256 of the normalised text, which
stands for the content itself.

An ``Index`` is stored: its keys with the filter of every shard, and the live
(digest, doc_id) pairs, from which a deletion finds the smallest id that is left.
``insert_batch``, ``delete_batch`` and ``is_live`` load the shards' stored filters;
an index that outgrows its shards is dealt anew from the stored keys.

Edge cases: a null text counts as empty; empty texts are equal to each other;
a text of white space alone normalises to one space; null ``doc_id`` sorts after
all others, so such a row stays only if its whole group has no id; deleting what
is not in the index changes nothing.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stalegrad.llm.common import WORD_BREAKS, fresh, written

SLOTS = 4
KICKS = 200
SHARD_KEYS = 1 << 15
KEYS = "shard int, digest binary, keep_id long, group_size long, filter binary"


class CuckooShard:
    """Filter and stored keys of one shard; keys are digests as bytes, each with [copies, least id]."""

    def __init__(self, buckets: int = 64):
        self.live: dict[bytes, list] = {}
        self._resize(max(2, 1 << (buckets - 1).bit_length()))

    def _resize(self, buckets: int) -> None:
        self.buckets = buckets
        self.table = np.zeros((buckets, SLOTS), dtype=np.uint16).tolist()
        self.stored: list[list[bytes] | None] = [None] * buckets

    def _place(self, key: bytes) -> tuple[int, int, int]:
        mark = int.from_bytes(key[:2], "little") or 1
        first = int.from_bytes(key[2:10], "little") & (self.buckets - 1)
        return mark, first, self._other(first, mark)

    def _other(self, at: int, mark: int) -> int:
        return at ^ ((mark * 0x5BD1E995) & (self.buckets - 1))

    def __contains__(self, key: bytes) -> bool:
        mark, a, b = self._place(key)
        if mark not in self.table[a] and mark not in self.table[b]:
            return False
        return key in (self.stored[a] or ())  # verify: the filter may be wrong

    def insert(self, key: bytes, copies: int = 1, least: int | None = None) -> bool:
        """True if the key was not live before; else its group takes the copies and the smaller id."""
        if key in self:
            group = self.live[key]
            group[0] += copies
            if group[1] is None or (least is not None and least < group[1]):
                group[1] = least
            return False
        self.live[key] = [copies, least]
        self._keep(key)
        if not self._mark(key):
            self._rebuild(self.buckets * 2)
        return True

    def _keep(self, key: bytes) -> None:
        at = self._place(key)[1]
        if self.stored[at] is None:
            self.stored[at] = []
        self.stored[at].append(key)

    def _mark(self, key: bytes) -> bool:
        mark, a, b = self._place(key)
        for at in (a, b):
            row = self.table[at]
            if 0 in row:
                row[row.index(0)] = mark
                return True
        at = b
        for kick in range(KICKS):
            row = self.table[at]
            slot = (mark + kick) % SLOTS
            mark, row[slot] = row[slot], mark
            at = self._other(at, mark)
            row = self.table[at]
            if 0 in row:
                row[row.index(0)] = mark
                return True
        return False

    def _rebuild(self, buckets: int) -> None:
        while True:
            self._resize(buckets)
            for key in self.live:
                self._keep(key)
            if all(self._mark(key) for key in self.live):
                return
            buckets *= 2

    def delete(self, key: bytes, copies: int = 1) -> bool:
        """True if that was the last live copy."""
        if key not in self:
            return False
        self.live[key][0] -= copies
        if self.live[key][0] > 0:
            return False
        del self.live[key]
        mark, a, b = self._place(key)
        self.stored[a].remove(key)
        row = self.table[a] if mark in self.table[a] else self.table[b]
        row[row.index(mark)] = 0
        return True

    def rows(self, shard: int) -> pa.Table:
        """The live keys, and one row without digest that holds the filter."""
        keys = list(self.live)
        table = np.array(self.table, dtype=np.uint16).tobytes()
        columns = {
            "shard": pa.array([shard] * (len(keys) + 1), pa.int32()),
            "digest": pa.array([*keys, None], pa.binary()),
            "keep_id": pa.array([*(self.live[k][1] for k in keys), None], pa.int64()),
            "group_size": pa.array([*(self.live[k][0] for k in keys), 0], pa.int64()),
            "filter": pa.array([None] * len(keys) + [table], pa.binary()),
        }
        return pa.table(columns)

    @classmethod
    def load(cls, table: pa.Table) -> CuckooShard:
        """The shard of stored rows: its filter as it was, the keys by bucket."""
        shard, filters = cls(), []
        for digest, least, copies, marks in zip(*(table.column(c).to_pylist() for c in ("digest", "keep_id", "group_size", "filter")), strict=True):
            if digest is None:
                filters.append(marks)
            else:
                shard.live[digest] = [copies, least]
        if len(filters) == 1:
            marks = np.frombuffer(filters[0], dtype=np.uint16).reshape(-1, SLOTS)
            shard._resize(len(marks))
            shard.table = marks.tolist()
            for key in shard.live:
                shard._keep(key)
        else:  # dealt anew: no filter fits these keys
            shard._rebuild(max(64, 1 << (len(shard.live) // 2).bit_length()))
        return shard


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), WORD_BREAKS, " ")


def _digests(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.unhex(F.sha2(normalised(F.col("text")), 256)).alias("digest"))


def _combined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(digest, least, copies) with the copies of one batch together."""
    for batch in batches:
        if batch.num_rows:
            t = pa.Table.from_batches([batch]).group_by("digest").aggregate([("doc_id", "min"), ([], "count_all")])
            yield from pa.table([t.column("digest").cast(pa.binary()), t.column("doc_id_min"), t.column("count_all").cast(pa.int64())], names=["digest", "least", "copies"]).to_batches()


def _arrivals(rows: DataFrame, shards: int) -> DataFrame:
    """shard, digest, least, copies of (doc_id, digest) rows."""
    light = rows.select("doc_id", "digest").mapInArrow(_combined, "digest binary, least long, copies long")
    return light.withColumn("shard", _shard(shards))


def _shard(shards: int) -> Column:
    return F.pmod(F.xxhash64("digest"), F.lit(shards)).cast("int")


def absorb(shard: CuckooShard, arrivals: pa.Table) -> CuckooShard:
    for key, least, copies in zip(*(arrivals.column(c).to_pylist() for c in ("digest", "least", "copies")), strict=True):
        shard.insert(key, copies, least)
    return shard


def _absorbed(arrivals: pa.Table) -> pa.Table:
    return absorb(CuckooShard(), arrivals).rows(arrivals.column("shard")[0].as_py())


def _shards_for(rows: int) -> int:
    return max(1, -(-rows // SHARD_KEYS))


def digest_index(rows: DataFrame, shards: int | None = None) -> DataFrame:
    """The keys and filters (``KEYS``) of (doc_id, digest) rows, one cuckoo shard a group of digests."""
    shards = _shards_for(rows.count()) if shards is None else shards
    return _arrivals(rows, shards).groupBy("shard").applyInArrow(_absorbed, KEYS)


@dataclass
class Index:
    """A stored index: keys with the filters, live (digest, doc_id, copies), number of shards."""

    keys: DataFrame
    members: DataFrame
    shards: int

    def groups(self) -> DataFrame:
        """digest, keep_id, group_size of the live digests."""
        return self.keys.where("digest IS NOT NULL").select("digest", "keep_id", "group_size")


def _met(index: Index, arrivals: DataFrame, step, schema: str = KEYS) -> DataFrame:
    """``step(shard number, loaded shard, its arrivals)`` for every shard that either side has."""

    def meet(left: pa.Table, right: pa.Table) -> pa.Table:
        number = (left if left.num_rows else right).column("shard")[0].as_py()
        return step(number, CuckooShard.load(left) if left.num_rows else CuckooShard(), right)

    return index.keys.groupBy("shard").cogroup(arrivals.groupBy("shard")).applyInArrow(meet, schema)


def _dealt_anew(index: Index, shards: int) -> Index:
    """The same keys over another number of shards; the filters are rebuilt when the shards are loaded."""
    keys = index.keys.where("digest IS NOT NULL").withColumn("shard", _shard(shards)).withColumn("filter", F.lit(None).cast("binary"))
    return Index(written(keys, "keys"), index.members, shards)


def insert_batch(index: Index | None, docs: DataFrame) -> Index:
    """The index with the documents of ``docs`` (doc_id, text) added, written anew."""
    rows = written(_digests(docs), "digests")
    more = rows.groupBy("digest", "doc_id").agg(F.count(F.lit(1)).alias("copies"))
    if index is None:
        shards = _shards_for(rows.count())
        return Index(written(digest_index(rows, shards), "keys"), written(more, "members"), shards)
    wanted = _shards_for(rows.count() + index.keys.count())
    if wanted > 2 * index.shards:
        index = _dealt_anew(index, wanted)
    keys = _met(index, _arrivals(rows, index.shards), lambda number, shard, new: absorb(shard, new).rows(number))
    members = index.members.unionByName(more).groupBy("digest", "doc_id").agg(F.sum("copies").alias("copies"))
    return Index(written(keys, "keys"), written(members, "members"), index.shards)


def delete_batch(index: Index, docs: DataFrame) -> Index:
    """The index after the rows of ``docs`` (doc_id, text) left; a group whose smallest id goes gets the next one."""
    gone = _digests(docs).groupBy("digest", "doc_id").agg(F.count(F.lit(1)).alias("gone"))
    none = F.lit(0).cast("long")
    both = index.members.select("digest", "doc_id", "copies", none.alias("gone")).unionByName(gone.select("digest", "doc_id", none.alias("copies"), "gone"))
    netted = written(both.groupBy("digest", "doc_id").agg(F.sum("copies").alias("copies"), F.least(F.sum("gone"), F.sum("copies")).alias("gone")), "netted")
    members = netted.where("copies > gone").select("digest", "doc_id", (F.col("copies") - F.col("gone")).alias("copies"))
    leaving = netted.where("gone > 0").groupBy("digest").agg(F.sum("gone").alias("copies"), F.min("doc_id").alias("least"))
    leaving = written(leaving, "leaving")

    def retire(number: int, shard: CuckooShard, old: pa.Table) -> pa.Table:
        for key, copies in zip(old.column("digest").to_pylist(), old.column("copies").to_pylist(), strict=True):
            shard.delete(key, copies)
        return shard.rows(number)

    keys = written(_met(index, leaving.withColumn("shard", _shard(index.shards)), retire), "keys")
    heirs = members.join(leaving.select("digest"), "digest", "left_semi").groupBy("digest").agg(F.min("doc_id").alias("_heir"))
    heirs = written(heirs.withColumn("_touched", F.lit(True)), "heirs")
    keys = keys.join(heirs, "digest", "left").withColumn("keep_id", F.when(F.col("_touched"), F.col("_heir")).otherwise(F.col("keep_id")))
    return Index(written(keys.select("shard", "digest", "keep_id", "group_size", "filter"), "keys"), written(members, "members"), index.shards)


def is_live(index: Index, docs: DataFrame) -> DataFrame:
    """docs with a boolean ``live``: whether the stored filters and keys have an equal text."""
    name = fresh(docs, "_digest")

    def look(number: int, shard: CuckooShard, probes: pa.Table) -> pa.Table:
        keys = probes.column("digest").to_pylist()
        return pa.table([pa.array(keys, pa.binary()), pa.array([key in shard for key in keys], pa.bool_())], names=["digest", "live"])

    keyed = docs.withColumn(name, F.unhex(F.sha2(normalised(F.col("text")), 256)))
    probes = keyed.select(F.lit(None).cast("long").alias("doc_id"), F.col(name).alias("digest"))
    found = _met(index, _arrivals(probes, index.shards), look, "digest binary, live boolean")
    found = written(found.groupBy("digest").agg(F.max("live").alias("live")), "live").withColumnRenamed("digest", name)
    return keyed.join(found, name).drop(name).select(*docs.columns, "live")


def exact_groups(docs: DataFrame) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 for every row.

    Rows with the same id and text all count as kept when that id is the
    smallest; ``drop_exact`` keeps one of them.
    """
    rows = written(_digests(docs), "digests")
    index = written(digest_index(rows), "keys").where("digest IS NOT NULL")  # written, so that the join can split a hot digest
    kept = F.coalesce(F.col("doc_id") == F.col("keep_id"), F.col("keep_id").isNull())
    return rows.join(index, "digest").select("doc_id", "keep_id", "group_size", kept.alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"))


def drop_exact(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` with one row of each group of equal texts, the smallest doc_id."""
    digest, keep, size = (fresh(docs, f"_xd_{c}") for c in ("digest", "keep", "size"))
    keyed = docs.withColumn(digest, F.unhex(F.sha2(normalised(F.col("text")), 256)))
    light = written(_digests(docs), "digests")
    index = written(digest_index(light), "keys").where("digest IS NOT NULL")
    index = index.select(F.col("digest").alias(digest), F.col("keep_id").alias(keep), F.col("group_size").alias(size))
    first = keyed.join(index, digest).where(F.coalesce(F.col("doc_id").cast("long") == F.col(keep), F.col(keep).isNull()))
    # repeated rows: ids that are still there twice are brought down to one row
    single, many = first.where(F.col(size) == 1), first.where(F.col(size) > 1)
    return single.unionByName(many.dropDuplicates([digest])).select(*docs.columns)
