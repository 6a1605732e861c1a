"""Rows that carry a packed array for each bucket of a hash, instead of one row for each entry."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import SparkSession


def bucket_bits(spark: SparkSession) -> int:
    """Bits of the hash that name a bucket: sixteen buckets a shuffle partition, 4096 at least."""
    return max(12, (16 * int(spark.conf.get("spark.sql.shuffle.partitions")) - 1).bit_length())


def bucket_runs(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, list[dict]]]:
    """Rows of one bucket after another, from rows sorted by bucket."""
    at, rows = None, []
    for batch in batches:
        for row in batch.to_pylist():
            if row["bucket"] != at:
                if rows:
                    yield at, rows
                at, rows = row["bucket"], []
            rows.append(row)
    if rows:
        yield at, rows
