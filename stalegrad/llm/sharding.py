"""Proportional stratified interleaving into shards.

Rows are shuffled by a seeded hash within their source, given the fractional
rank (r + u) / n of their source with one hashed offset u in [0, 1) a source,
sorted by it over all sources and cut into runs whose row counts differ by at
most one.  A shard's share of every source then differs from the mixture's by
less than a row or two.

Ranks are exact at any size: rows are dealt by (source, hash bucket) or by
fractional-rank bucket, and the bucket counts give the offsets, so a source with
a third of all rows is not one task.

Edge cases: a null source is a source of its own; null texts have size 1; ties
of the hash are broken by id, size and checksum (equal rows may swap); an empty
table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from stalegrad.llm.common import fresh, ranked, unit_hash

ROWS_PER_BUCKET = 2_000


def positions(rows: DataFrame, stratum: Column, seed: int, ties: list[str], total: int | None = None) -> DataFrame:
    """``rows`` plus ``position``: the place from 0 in the interleaved order."""
    total = rows.count() if total is None else total
    buckets = max(1, -(-total // ROWS_PER_BUCKET))
    keyed = rows.withColumns({"_stratum": F.coalesce(F.concat(F.lit("="), stratum.cast("string")), F.lit("null")), "_unit": unit_hash(F.col("doc_id"), seed=seed)})
    order = [F.col(c) for c in ("_unit", *ties)]
    sized = ranked(keyed, ["_stratum"], order, F.col("_unit"), buckets, "_rank")
    sizes = keyed.groupBy("_stratum").agg(F.count(F.lit(1)).alias("_n"))
    placed = sized.join(sizes, "_stratum").withColumn("_fraction", (F.col("_rank") + unit_hash(F.col("_stratum"), seed=seed)) / F.col("_n")).withColumn("_all", F.lit(0))
    return ranked(placed, ["_all"], [F.col(c) for c in ("_fraction", "_stratum", "_rank")], F.col("_fraction"), buckets, "position").drop("_all", "_fraction", "_n", "_rank", "_unit", "_stratum")


def cut(placed: DataFrame, n_shards: int, total: int) -> DataFrame:
    """Adds ``shard`` and ``slot``: equal runs of positions, the first ``total % n`` one longer."""
    base, extra = divmod(total, n_shards)
    edge = extra * (base + 1)
    at = F.col("position")
    shard = F.when(at < edge, F.floor(at / F.lit(base + 1))).otherwise(F.lit(extra) + F.floor((at - edge) / F.lit(max(base, 1))))
    shard = shard.cast("int")
    start = F.when(shard < extra, shard * F.lit(base + 1)).otherwise(F.lit(edge) + (shard - extra) * F.lit(base))
    return placed.withColumn("shard", shard).withColumn("slot", (at - start).cast("long"))


def stratified_shards(docs: DataFrame, n_shards: int = 8, seed: int = 0) -> DataFrame:
    """doc_id, source, size, text_crc32, shard, slot for every row of ``docs``."""
    rows = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.col("source").alias("source"),
        (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long").alias("size"),
        F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")).alias("text_crc32"),
    )
    total = docs.count()
    return cut(positions(rows, F.col("source"), seed, ["doc_id", "size", "text_crc32"], total), n_shards, total).drop("position")


def write_shards(docs: DataFrame, path: str, n_shards: int = 8, seed: int = 0) -> None:
    """Writes whole rows of ``docs`` under ``path/shard=K``, each shard in slot order.

    Rows meet their place on (doc_id, checksum, size, source); rows equal in all
    of them are copies of each other and take the places of the group in any order.
    Where ``docs`` has a column shard or slot, the new ones
    get an underscore in front.
    """
    shard, slot, mark, copy = (fresh(docs, c) for c in ("shard", "slot", "_mark", "_copy"))
    parts = {"i": F.col("doc_id").cast("long"), "c": F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")), "s": (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long"), "o": F.coalesce(F.col("source"), F.lit(""))}
    left = docs.withColumn(mark, F.struct(*[c.alias(k) for k, c in parts.items()]))
    places = stratified_shards(docs, n_shards, seed)
    own = F.struct(F.col("doc_id").alias("i"), F.col("text_crc32").alias("c"), F.col("size").alias("s"), F.coalesce(F.col("source"), F.lit("")).alias("o"))
    right = places.select(own.alias(mark), F.col("shard").alias(shard), F.col("slot").alias(slot))
    left = left.withColumn(copy, F.row_number().over(Window.partitionBy(mark).orderBy(F.lit(0))))
    right = right.withColumn(copy, F.row_number().over(Window.partitionBy(mark).orderBy(shard, slot)))
    done = left.join(right, [mark, copy]).drop(mark, copy)
    done.repartitionByRange(shard, slot).sortWithinPartitions(shard, slot).write.partitionBy(shard).parquet(path)
