"""Token ids, exact length histograms and best-fit packing plans.

Ids are those of a byte-level BPE file (``tokenizers`` JSON).  When the file is
plain (no normaliser, no post-processor, standard split, merges in id order) its
merges run through a faster engine with the same ids, which the tests hold
against the ``tokenizers`` library; any other file runs through that library.
Strings of special tokens in a text are ordinary text.

Edge cases: a null text is the empty text; an empty text has the end id only
when one is asked for.
"""

from __future__ import annotations

import json
import os
import zlib
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stalegrad.llm.common import ranked, running_totals, unit_hash, written

#: The published split pattern of byte-level BPE with its quantifiers
#: made possessive, which gives the same pieces without backtracking.
SPLIT = r"'(?:[sdmt]|ll|ve|re)| ?\p{L}++| ?\p{N}++| ?[^\s\p{L}\p{N}]++|\s++$|\s+(?!\S)|\s"


def tokenizer_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _letters() -> dict[str, int]:
    """The printable letter that stands for each byte in byte-level BPE files."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


@lru_cache(maxsize=2)
def encoder(path: str) -> Callable[[str], list[int]]:
    """text -> ids, loaded once in each Python worker."""
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    spec = json.load(open(path, encoding="utf-8"))
    model, pre = spec["model"], spec.get("pre_tokenizer") or {}
    plain = spec.get("normalizer") is None and spec.get("post_processor") is None and model.get("type") == "BPE" and pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True)
    plain = plain and not any(model.get(k) for k in ("dropout", "unk_token", "continuing_subword_prefix", "end_of_word_suffix", "fuse_unk", "byte_fallback", "ignore_merges"))
    if plain:
        special = {t["content"] for t in spec.get("added_tokens", [])}
        letters = _letters()
        ranks = {bytes(letters[c] for c in word): i for word, i in model["vocab"].items() if word not in special}
        merges = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
        if all(model["vocab"].get("".join(m)) == 256 + i for i, m in enumerate(merges)) and len(ranks) == 256 + len(merges):
            import tiktoken

            return tiktoken.Encoding("file", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    tokenizer.encode_special_tokens = True
    return lambda text: tokenizer.encode(text, add_special_tokens=False).ids


def token_lengths(docs: DataFrame, path: str, keep: list[str] = ()) -> DataFrame:
    """``n_tokens`` of every text, beside the columns of ``keep``."""
    keep = [c for c in keep]
    picked = docs.select(*[F.col(c).alias(f"_k{i}") for i, c in enumerate(keep)], F.col("text").alias("_text"))

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(path)
        for batch in batches:
            n = np.fromiter((len(encode(x)) if x else 0 for x in _texts(batch.column("_text"))), dtype=np.int64, count=batch.num_rows)
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], pa.array(n)], names=[*batch.schema.names[: len(keep)], "n_tokens"])

    fields = ", ".join([*(f"_k{i} {t}" for i, (_, t) in enumerate(picked.dtypes[: len(keep)])), "n_tokens long"])
    return picked.mapInArrow(measure, fields).toDF(*keep, "n_tokens")


def _texts(column: pa.Array) -> Iterator[str | None]:
    """Texts one by one, so that a batch is not held twice."""
    for x in column:
        yield x.as_py()


def length_histogram(lengths: DataFrame) -> DataFrame:
    """Exact counts by length with suffix sums; each row answers its length as a context limit.

    Columns: n_tokens, n_docs, docs_at_least, tokens_at_least (documents and
    tokens in documents of that length or longer), docs_below, tokens_below, and
    truncated_tokens: the total if every document is cut at ``n_tokens``.
    """
    counts = written(lengths.groupBy("n_tokens").agg(F.count(F.lit(1)).alias("n_docs")), "lengths").withColumn("_tokens", F.col("n_tokens") * F.col("n_docs"))
    ahead = running_totals(counts, "n_tokens", ["n_docs", "_tokens"], descending=True).withColumnsRenamed({"run_n_docs": "docs_at_least", "run__tokens": "tokens_at_least"})
    below = running_totals(ahead, "n_tokens", ["n_docs", "_tokens"])
    n, own = F.col("n_tokens"), F.col("_tokens")
    return below.select(
        "n_tokens", "n_docs", "docs_at_least", "tokens_at_least",
        (F.col("run_n_docs") - F.col("n_docs")).alias("docs_below"),
        (F.col("run__tokens") - own).alias("tokens_below"),
        (F.col("run__tokens") - own + n * F.col("docs_at_least")).alias("truncated_tokens"),
    )


def quantiles(histogram: DataFrame, levels: list[float]) -> DataFrame:
    """level, n_tokens: the least length that at least that share of documents does not exceed."""
    total = histogram.agg(F.sum("n_docs").alias("_all"))
    asked = histogram.sparkSession.createDataFrame([(float(x),) for x in levels], "level double")
    upto = histogram.select("n_tokens", (F.col("docs_below") + F.col("n_docs")).alias("_upto"))
    return upto.crossJoin(F.broadcast(total)).join(F.broadcast(asked), F.col("_upto") >= F.col("level") * F.col("_all")).groupBy("level").agg(F.min("n_tokens").alias("n_tokens"))


def truncated_totals(histogram: DataFrame, limits: list[int]) -> DataFrame:
    """context_limit, truncated_tokens, docs_cut: totals if every document is cut at the limit.

    ``limits`` is a short list of the caller, so it is broadcast.
    """
    asked = histogram.sparkSession.createDataFrame([(int(x),) for x in limits], "context_limit long")
    n, limit = F.col("n_tokens"), F.col("context_limit")
    return histogram.select("n_tokens", "n_docs").join(F.broadcast(asked), F.lit(True)).groupBy("context_limit").agg(
        F.sum(F.least(n, limit) * F.col("n_docs")).alias("truncated_tokens"), F.sum(F.when(n > limit, F.col("n_docs")).otherwise(0)).alias("docs_cut")
    )


def pieces(docs: DataFrame, path: str, limit: int, end_id: int) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32: documents with their end id, cut at ``limit``.

    Only longer documents are cut; all pieces but the first have ``limit`` ids.
    """

    def encode_all(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(path)
        for batch in batches:
            out: list[tuple[int | None, int, int, int, int]] = []
            for doc, text in zip(batch.column("doc_id").to_pylist(), _texts(batch.column("text")), strict=True):
                ids = np.array([*(encode(text) if text else ()), end_id], dtype="<u4")
                first = len(ids) % limit or limit
                start, size, k = 0, min(first, len(ids)), 0
                while start < len(ids):
                    out.append((doc, k, start, size, zlib.crc32(ids[start : start + size].tobytes())))
                    start, size, k = start + size, limit, k + 1
            cols = list(zip(*out, strict=True)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(encode_all, "doc_id long, piece int, start long, length long, ids_crc32 long")


def best_fit_plan(counts: dict[int, int], limit: int) -> list[tuple[int, int, int, int, int, int]]:
    """Best fit, longest first, over counts of lengths.

    Gives (length, first rank, end rank, per_bin, first sequence, offset): the
    item of rank r goes to sequence first + (r - first rank) // per_bin at
    offset + ((r - first rank) % per_bin) * length.  Open sequences are held as
    runs by the room they have left, so the work depends on the number of
    different lengths, never on the number of items.
    """
    room: dict[int, list[tuple[int, int]]] = {}  # room left -> runs (first sequence, how many)
    plan: list[tuple[int, int, int, int, int, int]] = []
    opened = 0

    def put(left: int, run: tuple[int, int]) -> None:
        if left and run[1]:
            room.setdefault(left, []).append(run)

    for length in sorted(counts, reverse=True):
        todo, rank = counts[length], 0
        for left in sorted(r for r in room if r >= length):
            if not todo:
                break
            per = left // length
            runs = room.pop(left)
            while runs and todo:
                first, many = runs.pop()
                full = min(many, todo // per)
                if full:
                    plan.append((length, rank, rank + full * per, per, first, limit - left))
                    put(left - per * length, (first, full))
                    rank, todo = rank + full * per, todo - full * per
                if full < many and todo:  # the rest is fewer than one sequence takes
                    plan.append((length, rank, rank + todo, todo, first + full, limit - left))
                    put(left - todo * length, (first + full, 1))
                    rank, full, todo = rank + todo, full + 1, 0
                if full < many:
                    runs.append((first + full, many - full))
            if runs:
                room.setdefault(left, []).extend(runs)
        if todo:
            per = limit // length
            full, rest = divmod(todo, per)
            if full:
                plan.append((length, rank, rank + full * per, per, opened, 0))
                put(limit - per * length, (opened, full))
            if rest:
                plan.append((length, rank + full * per, rank + todo, rest, opened + full, 0))
                put(limit - rest * length, (opened + full, 1))
            opened += full + bool(rest)
    return plan


def pack(docs: DataFrame, path: str, limit: int = 1024, end_id: int = 2) -> DataFrame:
    """Pieces with their planned sequence_id and offset.

    The histogram has at most ``limit`` rows, and so has the driver; the plan has
    a few intervals a length (at most ``limit`` squared), so it is broadcast.
    Ranks within a length are exact by bucketed counts, whatever length is
    common.
    """
    cut = written(pieces(docs, path, limit, end_id), "pieces")
    counts = {int(r["length"]): int(r["n"]) for r in cut.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}
    plan = best_fit_plan(counts, limit)
    spark = docs.sparkSession
    slots = spark.createDataFrame(plan, "length long, lo long, hi long, per_bin long, first long, base long")
    buckets = max(1, -(-sum(counts.values()) // 20_000))
    order = [F.col(c) for c in ("_unit", "doc_id", "piece", "start", "ids_crc32")]
    spread = cut.withColumn("_unit", unit_hash("doc_id", "piece", "ids_crc32"))
    numbered = ranked(spread, ["length"], order, F.col("_unit"), buckets, "_rank").drop("_unit")
    seat = F.col("_rank") - F.col("lo")
    joined = numbered.join(F.broadcast(slots), "length").where((F.col("_rank") >= F.col("lo")) & (F.col("_rank") < F.col("hi")))
    return joined.select(
        "doc_id", "piece", "start", "length", "ids_crc32",
        (F.col("first") + F.floor(seat / F.col("per_bin"))).cast("long").alias("sequence_id"),
        (F.col("base") + (seat % F.col("per_bin")) * F.col("length")).cast("long").alias("offset"),
    )
