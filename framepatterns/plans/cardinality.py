"""How many distinct keys, and how far a local combine would shrink the data."""

from __future__ import annotations

import math
from collections import OrderedDict
from collections.abc import Iterator
from functools import reduce
from operator import and_

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def cardinality(df: DataFrame, keys: list[str], mode: str = "hll") -> float:
    """Distinct keys per row, between 1/N and 1: exact, or by a sketch."""
    key = F.struct(*keys)
    distinct = F.count_distinct(key) if mode == "exact" else F.approx_count_distinct(F.xxhash64(*keys), 0.01)
    n, d = df.agg(F.count("*"), distinct).first()
    return min(1.0, d / n) if n else 1.0


def modelled_ratio(rows: int, distinct: int, partitions: int) -> float:
    """Expected share of rows left by a local combine when keys are equally frequent and dealt at random."""
    if not rows or not distinct:
        return 1.0
    return min(1.0, partitions * distinct * (1 - (1 - 1 / partitions) ** (rows / distinct)) / rows)


_KNOWN: OrderedDict[tuple, float] = OrderedDict()
_REMEMBER = 256


#: Keys that wait, at least, before they are merged with those seen.
_WAIT = 1 << 18


def _distinct(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(rows, distinct keys) of one partition.

    Keys wait until there are as many as are seen already, so merging does not grow with rows times keys.
    """
    seen, new, n, waiting = np.zeros(0, np.int64), [], 0, 0
    for b in batches:
        n += b.num_rows
        new.append(b.column(0).to_numpy(zero_copy_only=False).copy())
        waiting += b.num_rows
        if waiting >= max(_WAIT, seen.size):
            seen, new, waiting = np.unique(np.concatenate([seen, *new])), [], 0
    seen = np.unique(np.concatenate([seen, *new]))
    yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([seen.size])], names=["n", "d"])


def whole_ratio(df: DataFrame, keys: list[str]) -> float:
    """Share of rows left by a combine of all rows in one place, without bringing them there; NaN where there are none.

    Partitions combine first and only what they leave is dealt, so neither a single task nor a hot key holds it up.
    As in SQL's count of distinct values, rows with a null in the key count, but are no key.
    """
    left = df.groupBy(*keys).agg(F.count("*").alias("_n"))
    n, d = left.agg(F.sum("_n"), F.count_if(reduce(and_, [F.col(c).isNotNull() for c in keys]))).first()
    return d / n if n else math.nan


def combine_ratio(df: DataFrame, keys: list[str], splits: int = 8) -> float:
    """Measured share of rows left by a local combine, on at most ``splits`` whole partitions.

    Only these partitions' tasks run, so the read does not grow with the input; row samples would bias the share
    upward.  It is remembered for each plan and key, for as long as the program runs: data that change under
    the same plan can make a choice slower, never wrong.
    """
    name = (df.sparkSession.sparkContext.applicationId, df.semanticHash(), tuple(keys), splits)
    if name not in _KNOWN:
        counted = df.select(F.xxhash64(*keys).alias("h")).mapInArrow(_distinct, "n long, d long").rdd
        parts = counted.getNumPartitions()
        some = sorted({parts * i // splits for i in range(splits)}) if parts else []
        found = df.sparkSession.sparkContext.runJob(counted, list, some) if some else []
        rows = sum(r.n for r in found)
        _KNOWN[name] = sum(r.d for r in found) / rows if rows else 1.0
        while len(_KNOWN) > _REMEMBER:
            _KNOWN.popitem(last=False)
    return _KNOWN[name]
