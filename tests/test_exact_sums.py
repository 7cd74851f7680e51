"""Sums in hundredths do not depend on the order of the rows."""

from fractions import Fraction

from pyspark.sql import functions as F

from stalegrad.catalog import optimiser_queries as Q
from stalegrad.sources.tables import SCHEMAS, load


def test_sums_are_exact(spark, sf, tmp_path):
    prices = [1e11 + 0.25 * i for i in range(1500)] + [0.01] * 1501
    lines = load(spark, sf, "lineitem").limit(1).drop("l_extendedprice", "l_partkey")
    part = load(spark, sf, "part").limit(1)
    priced = spark.createDataFrame([(p,) for p in prices], "l_extendedprice double").repartition(6)
    rows = priced.crossJoin(lines).crossJoin(part.select(F.col("p_partkey").alias("l_partkey")))
    rows.select(*[c.split()[0] for c in SCHEMAS["lineitem"].split(", ")]).write.parquet(f"{tmp_path}/lineitem.parquet")
    part.write.parquet(f"{tmp_path}/part.parquet")
    got = {r.col: r.sum_hundredths for r in Q.standardized_stats(spark, str(tmp_path)).collect()}
    assert got["l_extendedprice"] == round(sum(map(Fraction, prices)) * 100)
