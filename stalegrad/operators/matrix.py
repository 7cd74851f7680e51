"""Matrix preparation: row ids, standardised features, indicator columns, loads and bytes."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from stalegrad.sources.tables import written


def standardize(df: DataFrame, cols: list[str]) -> tuple[DataFrame, DataFrame]:
    """Columns to mean 0 and variance 1 (constant columns to 0), and the one-row statistics."""
    stats = df.agg(*[F.avg(c).alias(f"m_{c}") for c in cols], *[F.stddev_pop(c).alias(f"s_{c}") for c in cols])
    joined = df.crossJoin(F.broadcast(stats))  # one row of statistics
    scaled = {c: F.when(F.col(f"s_{c}") > 0, (F.col(c) - F.col(f"m_{c}")) / F.col(f"s_{c}")).otherwise(0.0) for c in cols}
    return joined.withColumns(scaled).drop(*[f"m_{c}" for c in cols], *[f"s_{c}" for c in cols]), stats


def add_intercept(df: DataFrame, features: str = "features") -> DataFrame:
    return df.withColumn(features, F.concat(features, F.array(F.lit(1.0))))


def row_digest(df: DataFrame, seed: int = 0):
    """MD5 over the seed and every column, the order that permutes the rows."""
    return F.md5(F.concat_ws("|", F.lit(str(seed)), *[F.coalesce(F.col(c).cast("string"), F.lit("~")) for c in df.columns]).cast("binary"))


def index_rows(df: DataFrame, seed: int = 0, strategy: str = "two_pass", digest=None) -> DataFrame:
    """Adds ``sample_idx``: contiguous from 1 in the order of a hash of the row.

    ``two_pass`` counts rows by the first hex digits of the hash, prefix-sums the
    counts and ranks inside each digit group, so no task holds more than one
    group; ``window`` is the single-task reference.
    """
    hashed = df.withColumn("_digest", row_digest(df, seed) if digest is None else digest)
    ties = [F.col(c) for c in df.columns]
    if strategy == "window":
        w = Window.orderBy("_digest", *ties)
        return hashed.withColumn("sample_idx", F.row_number().over(w).cast("long")).drop("_digest")
    grouped = hashed.withColumn("_group", F.conv(F.substring("_digest", 1, 4), 16, 10).cast("int"))
    counts = grouped.groupBy("_group").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.orderBy("_group").rowsBetween(Window.unboundedPreceding, -1)  # at most 65,536 rows
    offsets = counts.select("_group", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    inside = Window.partitionBy("_group").orderBy("_digest", *ties)
    ranked = grouped.withColumn("_at", F.row_number().over(inside)).join(F.broadcast(offsets), "_group")
    return ranked.withColumn("sample_idx", (F.col("_before") + F.col("_at")).cast("long")).drop("_digest", "_group", "_at", "_before")


def indicator_matrix(pairs: DataFrame, row_key: str, col_key: str) -> DataFrame:
    """(row_key, nz): sorted column numbers from 1 of each row; columns are numbered by value.

    The dictionary of distinct column values is sorted in ranges: rows of a range
    are ranked by themselves and the counts of the ranges before are added, so no
    task holds all of it.  The join takes its size into account (broadcast only if
    Spark finds it small).
    """
    cells = pairs.select(row_key, col_key).distinct()
    ranges = cells.select(col_key).distinct().repartitionByRange(col_key).withColumn("_range", F.spark_partition_id())
    names = written(ranges, "columns")  # once, so that the ranges stay as they are
    before = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)  # one row a range
    offsets = names.groupBy("_range").agg(F.count(F.lit(1)).alias("_n")).select("_range", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    at = F.row_number().over(Window.partitionBy("_range").orderBy(col_key))
    names = names.withColumn("_at", at).join(F.broadcast(offsets), "_range").select(col_key, (F.col("_before") + F.col("_at")).cast("int").alias("col_idx"))
    return cells.join(names, col_key).groupBy(row_key).agg(F.array_sort(F.collect_list("col_idx")).alias("nz"))


def density(pairs: DataFrame, row_key: str, col_key: str) -> DataFrame:
    cells = pairs.select(row_key, col_key).distinct()
    sizes = cells.agg(F.countDistinct(row_key).alias("n_rows"), F.countDistinct(col_key).alias("n_cols"), F.count(F.lit(1)).alias("nnz"))
    return sizes.withColumn("density", F.col("nnz") / (F.col("n_rows") * F.col("n_cols")))


def comp_load(rows: float, d: int, k: int, share: float = 1.0) -> float:
    """Operations of one subgradient: two products with the rows of the piece."""
    return 2.0 * share * rows * d * k


def comm_bytes(d: int, k: int, width: int = 4) -> int:
    """Bytes of an iterate sent each way."""
    return d * k * width


def coded_load(load: float, num: int, den: int) -> float:
    """Load of a worker under coding at rate num/den."""
    return load * den / num


def hash_sample(df: DataFrame, share: float, seed: int = 0) -> DataFrame:
    """Rows whose hashed uniform is below ``share``: the same rows under any partitioning."""
    return df.where(F.conv(F.substring(row_digest(df, seed), 1, 12), 16, 10).cast("double") < share * float(1 << 48))


#: Features of the logistic workload on lineitem joined with part.
LOGIT_COLUMNS = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "p_size", "p_retailprice"]


def logit_rows(lineitem: DataFrame, part: DataFrame, flip: float = 0.1, null_label: bool = False) -> DataFrame:
    """Raw features with a label in {-1, 1}; a tenth of the labels is flipped by a hash of the row."""
    joined = lineitem.join(part.select("p_partkey", "p_size", "p_retailprice"), F.col("l_partkey") == F.col("p_partkey"))
    key = F.md5(F.concat_ws("|", *[F.col(c).cast("string") for c in ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")]).cast("binary"))
    if null_label:
        label = F.when(F.col("l_returnflag") == "R", 1.0).otherwise(-1.0)
    else:
        over = F.col("l_extendedprice") * (1 - F.col("l_discount")) > 45_000
        turned = F.conv(F.substring(key, 1, 8), 16, 10).cast("double") < flip * 2**32
        label = F.when(over != turned, 1.0).otherwise(-1.0)
    return joined.select(*[F.col(c).cast("double").alias(c) for c in LOGIT_COLUMNS], label.alias("label"), key.alias("row_key"), "l_orderkey", "l_linenumber", "l_shipdate")


def logit_matrix(lineitem: DataFrame, part: DataFrame, seed: int = 0, flip: float = 0.1, null_label: bool = False, keep: bool = True) -> DataFrame:
    """sample_idx, label and the columns x0..x6 (standardised, last one 1)."""
    raw = logit_rows(lineitem, part, flip, null_label)
    scaled, _ = standardize(raw, LOGIT_COLUMNS)
    indexed = index_rows(scaled, seed, digest=F.md5(F.concat_ws("|", F.lit(str(seed)), "row_key").cast("binary")))
    out = indexed.select("sample_idx", "label", *[F.col(c).alias(f"x{i}") for i, c in enumerate(LOGIT_COLUMNS)], F.lit(1.0).alias(f"x{len(LOGIT_COLUMNS)}"))
    return sorted_rows(out, "logit") if keep else out


def sorted_rows(matrix: DataFrame, name: str) -> DataFrame:
    """The matrix written in row order, so that row ranges skip files and pages."""
    files = max(8, matrix.sparkSession.sparkContext.defaultParallelism)
    return written(matrix.repartitionByRange(files, "sample_idx").sortWithinPartitions("sample_idx"), name)


def document_matrix(documents: DataFrame, labels: DataFrame) -> DataFrame:
    """Quality labels against size features of documents, standardised: x0..x3 and label (few negatives)."""
    words = F.size(F.split(F.coalesce("text", F.lit("")), r"\s+"))
    raw = documents.join(labels, "doc_id").select("doc_id", F.log1p(F.col("n_chars").cast("double")).alias("a"), F.log1p(words.cast("double")).alias("b"), (F.length(F.regexp_replace("text", r"[^A-Z]", "")) / (1 + F.col("n_chars"))).alias("c"), F.when(F.col("quality") == 1, 1.0).otherwise(-1.0).alias("label"))
    scaled, _ = standardize(raw, ["a", "b", "c"])
    indexed = index_rows(scaled, digest=F.md5(F.col("doc_id").cast("string").cast("binary")))
    return written(indexed.select("sample_idx", "label", *[F.col(c).alias(f"x{i}") for i, c in enumerate("abc")], F.lit(1.0).alias("x3")), "quality")


def embedding_matrix(embeddings: DataFrame, positive: int = 0) -> DataFrame:
    """One label against the rest on the embedding columns and an intercept."""
    raw = embeddings.select("vec_id", F.when(F.col("label") == positive, 1.0).otherwise(-1.0).alias("label"), *[F.col("embedding")[i].cast("double").alias(f"x{i}") for i in range(64)], F.lit(1.0).alias("x64"))
    indexed = index_rows(raw, digest=F.md5(F.col("vec_id").cast("string").cast("binary")))
    return written(indexed.drop("vec_id"), "vectors")


def token_cells(documents: DataFrame, buckets: int = 2048) -> DataFrame:
    """(doc_id, col): buckets of the lower-cased [a-z0-9]+ tokens of each document."""
    tokens = F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit("[a-z0-9]+"), 0)))
    col = F.pmod(F.conv(F.substring(F.md5(F.col("token").cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(buckets))
    return documents.select("doc_id", tokens.alias("token")).select("doc_id", col.cast("int").alias("col")).distinct()


def token_matrix(documents: DataFrame, buckets: int = 2048, seed: int = 0) -> DataFrame:
    """sample_idx and nz (column numbers from 0) of the document indicator matrix."""
    rows = token_cells(documents, buckets).groupBy("doc_id").agg(F.array_sort(F.collect_set("col")).alias("nz"))
    return sorted_rows(index_rows(rows, seed, digest=F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("doc_id").cast("string")).cast("binary"))).select("sample_idx", "nz"), "tokens")
