"""Input frames of the experiments, derived from the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Key universe by cardinality, as (numerator, denominator) of the row count.
UNIVERSE = {0.9: (465, 100), 0.5: (6275, 10000), 0.1: (1, 10), 1e-3: (1, 1000), 1e-5: (1, 100000)}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def money(c: str | Column) -> Column:
    """Amounts hold two decimals; exact sums need them as decimals."""
    return (F.col(c) if isinstance(c, str) else c).cast("decimal(18,2)")


def universe(spark: SparkSession, sf_dir: str, c: float) -> int:
    a, b = UNIVERSE[c]
    return max(1, table(spark, sf_dir, "lineitem").count() * a // b)


def bench_a(spark: SparkSession, sf_dir: str, c: float) -> DataFrame:
    """Two 64-bit columns with distinct keys per row of about ``c``."""
    mix = F.col("l_orderkey") * 1000003 + F.col("l_partkey") * 10007 + F.col("l_suppkey") * 101 + F.col("l_linenumber").cast("long") * 13 + F.round("l_quantity").cast("long")
    return table(spark, sf_dir, "lineitem").select((mix % universe(spark, sf_dir, c)).alias("k"), F.col("l_linenumber").cast("long").alias("v"))


def bench_b(spark: SparkSession, sf_dir: str, c: float) -> DataFrame:
    """A second frame of the same shape with keys from other columns."""
    mix = F.col("l_partkey") * 1000003 + F.col("l_orderkey") * 7919 + F.round(F.col("l_extendedprice") * 100).cast("long")
    return table(spark, sf_dir, "lineitem").select((mix % universe(spark, sf_dir, c)).alias("k"), F.col("l_linenumber").cast("long").alias("v"))


def sql_a(c: float) -> str:
    a, b = UNIVERSE[c]
    return f"(SELECT (l_orderkey*1000003 + l_partkey*10007 + l_suppkey*101 + l_linenumber::BIGINT*13 + round(l_quantity)::BIGINT) % (SELECT greatest(1, count(*)*{a}//{b}) FROM lineitem) AS k, l_linenumber::BIGINT AS v FROM lineitem)"


def sql_b(c: float) -> str:
    a, b = UNIVERSE[c]
    return f"(SELECT (l_partkey*1000003 + l_orderkey*7919 + round(l_extendedprice*100)::BIGINT) % (SELECT greatest(1, count(*)*{a}//{b}) FROM lineitem) AS k, l_linenumber::BIGINT AS v FROM lineitem)"
