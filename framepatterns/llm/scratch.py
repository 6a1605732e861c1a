"""Lineage cuts and fixed-size filters that survive the loss of an executor.

Intermediate tables are written as Parquet below ``spark.checkpoint.dir`` (read from the session), which
every executor and the driver share.  Where the setting is missing, as in tests, a temporary folder is used.
"""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from framepatterns.session import shared_root


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


BATCH_BYTES = 4 << 20
ROWS_PER_FILE, FILE_BYTES = 100_000, 4 << 20
READ_ROWS = 256


def bound_batches(spark: SparkSession) -> None:
    """Keep Arrow batches to Python at BATCH_BYTES (or one row), so that long texts don't pile up in memory.

    This lowers a run-time setting of the session; a smaller value that is already set stays.
    """
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    with contextlib.suppress(Exception):  # versions without the setting bound batches by rows only
        now = spark.conf.get(key, None)
        if now is None or not now.isdigit() or not 0 < int(now) <= BATCH_BYTES:
            spark.conf.set(key, str(BATCH_BYTES))


@contextlib.contextmanager
def short_reads(spark: SparkSession) -> Iterator[None]:
    """Parquet read by what runs inside comes in batches of READ_ROWS rows; afterwards the session's setting is as it was.

    A column's batch is one array, grown by doubling: at the engine's 4096 rows those of long texts are tens of MB each.
    """
    key = "spark.sql.parquet.columnarReaderBatchSize"
    before = spark.conf.get(key, None)
    spark.conf.set(key, str(READ_ROWS if before is None else min(int(before), READ_ROWS)))
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(key)
        else:
            spark.conf.set(key, before)


def give_back() -> None:
    """Return memory that this process has freed to the system, where the C library can do so."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(Exception):  # malloc_trim is glibc's
        ctypes.CDLL(None).malloc_trim(0)


def map_batches(df: DataFrame, run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: T.StructType | str) -> DataFrame:
    """``df.mapInArrow(run, schema)`` whose tasks give back what they freed when they end.

    Workers are kept for later tasks, and with them everything that their allocator holds, beside a JVM that grows
    to its heap's limit.
    """

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            give_back()

    return df.mapInArrow(task, schema)


def pieces(rows: int, size: int = 0) -> int:
    """Files for at most ``rows`` rows of about ``size`` bytes together."""
    return max(1, -(-rows // ROWS_PER_FILE), -(-size // FILE_BYTES))


def few_pieces(df: DataFrame, each: int = FILE_BYTES, a_core: int = 2) -> DataFrame:
    """``df``, a table's rows, with small input partitions put together to ``each`` bytes, but for ``a_core`` a core at least.

    The size is the engine's estimate, from the files; where it has none, and for larger partitions, nothing changes.
    """
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    least = max(1, a_core * df.sparkSession.sparkContext.defaultParallelism)
    return df.coalesce(max(least, -(-size // each))) if size < FILE_BYTES << 20 else df


class Scratch:
    """A private folder of durable intermediate tables; the whole folder goes when the program ends."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark, self.n = spark, 0
        bound_batches(spark)
        self.root = f"{shared_root(spark)}/{label}_{uuid.uuid4().hex}"
        atexit.register(self.close)

    def save(self, df: DataFrame, rows: int | None = None) -> DataFrame:
        """Write ``df`` once and return the written table.

        Where the number of rows is known to be about ``rows`` at most, it goes to one file for each ROWS_PER_FILE: a
        file costs an executor several short-lived processes on a local file system.
        """
        self.n += 1
        path = f"{self.root}/t{self.n}"
        (df if rows is None else df.coalesce(pieces(rows))).write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path = path
        return out

    def drop(self, df: DataFrame) -> None:
        """Remove a table that no later step reads."""
        if path := getattr(df, "_scratch_path", None):
            _delete(self.spark, path)

    def close(self) -> None:
        with contextlib.suppress(Exception):
            _delete(self.spark, self.root)


def bitmap(keys: DataFrame, col: str, log2_bits: int) -> np.ndarray:
    """A bit set over the low ``log2_bits`` bits of a 64-bit column.

    Its size is fixed by the parameter, so it may be broadcast however large the table is; false positives
    grow with the table, false negatives never occur, and callers only use it to skip work.
    """
    slot = F.col(col).bitwiseAND(F.lit((1 << log2_bits) - 1))
    words = keys.select(slot.alias("s")).select(
        F.shiftright("s", 6).alias("w"), F.expr("shiftleft(1L, cast(s & 63 as int))").alias("b")
    )
    table = words.groupBy("w").agg(F.bit_or("b").alias("b")).toArrow()
    bits = np.zeros(1 << (log2_bits - 6), dtype=np.uint64)
    if table.num_rows:
        bits[table.column("w").to_numpy()] = table.column("b").to_numpy().view(np.uint64)
    return bits


def test_bits(bits: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Which uint64 keys may be in the bit set."""
    slot = keys & np.uint64(bits.size * 64 - 1)
    return ((bits[slot >> np.uint64(6)] >> (slot & np.uint64(63))) & np.uint64(1)).astype(bool)
