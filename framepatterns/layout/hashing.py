"""Hash partitioning."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def hash_pid(keys: list[str] | str, partitions: int, df: DataFrame | None = None) -> Column:
    """Partition id by key, the same that ``repartition(partitions, *keys)`` uses; "*" hashes whole rows of ``df``."""
    cols = df.columns if keys == "*" else [keys] if isinstance(keys, str) else keys
    return F.pmod(F.hash(*cols), F.lit(partitions)).cast("int")


def local_bucket(keys: list[str], buckets: int) -> Column:
    """A second, independent hash that splits a partition into cache-sized buckets."""
    return F.pmod(F.xxhash64(*keys), F.lit(buckets)).cast("int")


def split_counts(df: DataFrame, pid: Column) -> DataFrame:
    """Rows that each partition would send to each other: (source, target, rows)."""
    return df.groupBy(F.spark_partition_id().alias("source"), pid.alias("target")).agg(F.count("*").alias("rows"))


def salted(keys: list[str], salts: int, by: Column) -> Column:
    """A small number from a column other than the key, to split hot keys."""
    return F.pmod(F.xxhash64(*keys, by), F.lit(salts)).cast("int")
