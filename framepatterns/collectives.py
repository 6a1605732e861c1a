"""Communication routines for dataframes, arrays and scalars.  A Spark stage boundary is the superstep boundary."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows that gather() may bring to one place, and bytes that broadcast_frame() may replicate.
GATHER_ROWS, BROADCAST_BYTES = 1_000_000, 256 << 20


def shuffle(df: DataFrame, pid: Column | str, partitions: int) -> DataFrame:
    """All-to-all: each row goes to the partition that ``pid`` names (0 .. partitions-1)."""
    return df.repartitionById(partitions, F.col(pid) if isinstance(pid, str) else pid)


def shuffle_by_key(df: DataFrame, keys: list[str], partitions: int) -> DataFrame:
    """All-to-all by key hash, in the way that joins and aggregations recognise, so they add no exchange."""
    return df.repartition(partitions, *keys)


def scatter(spark: SparkSession, rows: list, schema, partitions: int) -> DataFrame:
    """Spread local rows over contiguous partitions of equal length, in order."""
    table = spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], _with_first(schema))
    n = max(len(rows), 1)
    return shuffle(table, F.floor(F.col("_at") * partitions / n).cast("int"), partitions).sortWithinPartitions("_at").drop("_at")


def _with_first(schema):
    from pyspark.sql import types as T

    schema = T._parse_datatype_string(schema) if isinstance(schema, str) else schema
    return T.StructType([T.StructField("_at", T.LongType()), *schema.fields])


def gather(df: DataFrame, limit: int = GATHER_ROWS) -> pa.Table:
    """All rows at the driver, refused beyond ``limit`` rows (one row more is fetched to tell)."""
    table = df.limit(limit + 1).toArrow()
    if table.num_rows > limit:
        raise MemoryError(f"gather of more than {limit} rows refused")
    return table


def gather_partition(df: DataFrame) -> DataFrame:
    """All rows in one partition, still distributed data; for results that are known to be small."""
    return df.coalesce(1)


def all_gather(df: DataFrame, limit: int = GATHER_ROWS) -> DataFrame:
    """A frame that every executor holds whole; its row count is checked first."""
    if df.limit(limit + 1).count() > limit:
        raise MemoryError(f"all-gather of more than {limit} rows refused")
    return F.broadcast(df)


def estimated_bytes(df: DataFrame) -> int:
    """Size of a frame by the optimizer's statistics."""
    return int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())


def broadcast_frame(df: DataFrame, limit: int = BROADCAST_BYTES) -> DataFrame:
    """Mark a frame for replication if its size allows: by the optimizer's estimate, or else by counting rows up to the limit."""
    if estimated_bytes(df) > limit:
        rows = limit // max(sum(64 if t == "string" else 16 for _, t in df.dtypes), 1)
        if df.limit(rows + 1).count() > rows:
            raise MemoryError(f"broadcast of more than {limit} bytes refused")
    return F.broadcast(df)


def broadcast_value(spark: SparkSession, value):
    return spark.sparkContext.broadcast(value)


def reduce(df: DataFrame, *aggs: Column) -> DataFrame:
    """One row of aggregates: partial per partition, final in one place."""
    return df.agg(*aggs)


def reduce_array(df: DataFrame, col: str, how: Callable[[Column], Column] = F.sum) -> DataFrame:
    """Element-wise reduction of an array column: (position, value), one row a position."""
    return df.select(F.posexplode(col).alias("position", "value")).groupBy("position").agg(how("value").alias("value"))


def all_reduce(df: DataFrame, *aggs: Column) -> DataFrame:
    """``df`` with the global aggregates in every row.  Stays lazy: the reduced row is broadcast, nothing is collected."""
    return df.join(F.broadcast(df.agg(*aggs)), how="cross")


def halo_exchange(df: DataFrame, at: str, back: int, ahead: int, block: int, total: int) -> DataFrame:
    """Blocks of ``block`` positions, each with copies of the ``back`` rows before it and the ``ahead`` rows after it.

    ``at`` is the global position of each of ``total`` rows.  A row goes to its own block and to all blocks whose
    reach holds it, however many neighbours that are.  Adds _block, and _home, which is false for copies.
    """
    last = max((total - 1) // block, 0)
    first = F.greatest(F.floor((F.col(at) - ahead) / block), F.lit(0))
    end = F.least(F.floor((F.col(at) + back) / block), F.lit(last))
    out = df.withColumn("_block", F.explode(F.sequence(first, end))).withColumn("_home", F.col("_block") == F.floor(F.col(at) / block))
    return shuffle(out, F.col("_block").cast("int"), last + 1)


def barrier_map(df: DataFrame, fn: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """Run ``fn`` in all partitions at once with a barrier before it; needs a slot for every partition."""

    def run(batches):
        from pyspark import BarrierTaskContext

        BarrierTaskContext.get().barrier()
        yield from fn(batches)

    return df.mapInArrow(run, schema, barrier=True)
