"""Writers: one file a partition, one file in all, bucketed tables, intermediate tables of one program."""

from __future__ import annotations

import atexit
import contextlib
import uuid

from pyspark.sql import DataFrame, SparkSession

from framepatterns.collectives import GATHER_ROWS
from framepatterns.session import shared_root


def write_partitioned(df: DataFrame, path: str, fmt: str = "parquet", by: list[str] | None = None, rows_per_file: int = 0, mode: str = "error", **options) -> None:
    """Every partition writes its own file (files of bounded length if asked), in folders by ``by``."""
    w = df.write.format(fmt).mode(mode).options(**options)
    if rows_per_file:
        w = w.option("maxRecordsPerFile", rows_per_file)
    (w.partitionBy(*by) if by else w).save(path)


def write_single(df: DataFrame, path: str, fmt: str = "parquet", limit: int = GATHER_ROWS, **options) -> None:
    """Gather, then one file; refused beyond ``limit`` rows."""
    if df.limit(limit + 1).count() > limit:
        raise MemoryError(f"a single file of more than {limit} rows is refused")
    df.coalesce(1).write.format(fmt).options(**options).save(path)


def write_bucketed(df: DataFrame, table: str, keys: list[str], buckets: int, sort: bool = True) -> None:
    """A table dealt by key hash, so later joins and aggregations on the keys move nothing."""
    w = df.write.bucketBy(buckets, *keys)
    (w.sortBy(*keys) if sort else w).mode("overwrite").saveAsTable(table)


def drop_folder(spark: SparkSession, path: str) -> None:
    with contextlib.suppress(Exception):  # at the end of the program the session may be gone
        p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def private_folder(spark: SparkSession, label: str) -> str:
    """A new name below the shared folder; what is written there goes when the program ends."""
    path = f"{shared_root(spark)}/{label}_{uuid.uuid4().hex}"
    atexit.register(drop_folder, spark, path)
    return path


def written_once(df: DataFrame, label: str) -> DataFrame:
    """``df`` as a written table: its rows are computed once, and every later read sees the same ones."""
    path = private_folder(df.sparkSession, label)
    write_partitioned(df, path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
