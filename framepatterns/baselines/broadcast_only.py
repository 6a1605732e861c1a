"""A system that only knows broadcast joins: fails, in a recorded way, where the small side does not fit, or joins piece by piece."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from operator import and_

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from framepatterns.collectives import estimated_bytes
from framepatterns.sources.writers import drop_folder, private_folder, write_partitioned

#: Bytes of rows that are replicated at once; the driver holds them several times over while it builds their table.
AT_ONCE = 32 << 20

#: Bytes of a row group of what pieces are read from: small, so that a piece skips the others'.
ROW_GROUP = 1 << 20


class MemoryGuard(Exception):
    """The replicated side is larger than an executor may hold."""


def guard(right: DataFrame, limit: int) -> None:
    size = estimated_bytes(right)
    if size > limit:
        raise MemoryGuard(f"right side of {size} bytes, limit {limit}")


def join(left: DataFrame, right: DataFrame, on: list[str], how: str = "inner", limit: int = 512 << 20) -> DataFrame:
    guard(right, limit)
    return left.join(F.broadcast(right), on, how)


def rows_at_once(right: DataFrame, at_once: int | None = None) -> int:
    return max(1, (at_once or AT_ONCE) // max(sum(64 if t == "string" else 16 for _, t in right.dtypes), 1))


def pieces(left: DataFrame, right: DataFrame, on: list[str], at_once: int | None = None) -> Iterator[DataFrame]:
    """Frames that together are the whole inner join, each with a piece of the right side that may be replicated at once.

    Both sides are written once, a file a task with its rows in the order of a hash of the key, which moves no row to
    another worker; a piece reads only the row groups and pages with its own part of either side, so the work follows
    the rows and not rows times pieces.  A part whose right side holds more than two pieces, from hot keys, is cut by
    the rows' numbers.  Take a frame's result before asking for the next, and only one piece is held at a time.
    """
    if len({tuple(dict(x.dtypes)[c] for c in on) for x in (left, right)}) > 1:
        raise ValueError("the keys of both sides need the same types")
    most = rows_at_once(right, at_once)
    parts = -(-right.count() // most)
    if parts <= 1:
        yield left.join(F.broadcast(right), on)
        return
    spark, folder = left.sparkSession, private_folder(left.sparkSession, "join_pieces")

    def dealt(df: DataFrame, name: str) -> DataFrame:
        own = df.where(reduce(and_, [F.col(c).isNotNull() for c in on])).withColumn("_part", F.pmod(F.xxhash64(*on), F.lit(parts)).cast("int"))
        write_partitioned(own.sortWithinPartitions("_part"), f"{folder}/{name}", **{"parquet.block.size": str(ROW_GROUP)})
        return spark.read.schema(own.schema).parquet(f"{folder}/{name}")

    try:
        l, r = dealt(left, "left"), dealt(right.withColumn("_i", F.monotonically_increasing_id()), "right")
        found = sorted(r.groupBy("_part").count().collect()) or [(0, 0)]
        for part, n in found:
            slices = -(-n // most) if n > 2 * most else 1
            for s in range(slices):
                own = r.where((F.col("_part") == part) & (F.col("_i") % slices == s)).drop("_part", "_i")
                yield l.where(F.col("_part") == part).drop("_part").join(F.broadcast(own), on)
    finally:
        drop_folder(spark, folder)


def join_by_pieces(left: DataFrame, right: DataFrame, on: list[str], at_once: int | None = None) -> DataFrame:
    """The whole inner join of a right side of any size: in one go where it may be replicated at once, else written piece by piece."""
    if right.count() <= rows_at_once(right, at_once):
        return left.join(F.broadcast(right), on)
    path, schema = private_folder(left.sparkSession, "joined"), None
    for piece in pieces(left, right, on, at_once):
        schema = piece.schema
        write_partitioned(piece.coalesce(left.sparkSession.sparkContext.defaultParallelism), path, mode="append")
    return left.sparkSession.read.schema(schema).parquet(path)


def transpose_blocks(df: DataFrame, index: str, columns: list[str]) -> DataFrame:
    """Block transpose without a shuffle: each partition turns its own rows, blocks stay where they are."""
    cell = lambda c: F.struct(F.col(index).alias("label"), F.col(c).alias("value"))
    packed = df.groupBy(F.spark_partition_id().alias("block")).agg(*[F.array_sort(F.collect_list(cell(c))).alias(c) for c in columns])
    return packed.unpivot(["block"], columns, "column", "cells")
