"""Regular samples of locally sorted partitions, and pivots from them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from framepatterns.collectives import gather
from framepatterns.layout.ranges import key_struct

#: Row number in its partition: the low bits of the id that Spark counts up in every partition.
_ROW_BITS = 33


def row_index() -> Column:
    """Place of a row in its partition, as the partition is now."""
    return F.monotonically_increasing_id().bitwiseAND(F.lit((1 << _ROW_BITS) - 1))


def regular_sample(df: DataFrame, keys: list[Column], per_partition: int, partitions: int | None = None) -> DataFrame:
    """(key): every n-th key of every locally sorted partition, about ``per_partition`` for each of ``partitions``.

    Places count, not values: a key that holds half of all rows holds half of the sample, and an outlier is one
    row.  Partitions start at different places of the stride, so many short ones are sampled evenly too.
    """
    narrow = df.select(key_struct(keys).alias("key"))
    want = per_partition * (partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    stride = max(1, df.count() // max(want, 1))
    first = F.pmod(F.spark_partition_id().cast("long") * 7919, F.lit(stride))
    placed = narrow.sortWithinPartitions("key").withColumn("_i", row_index() + first)
    return placed.where(F.pmod("_i", F.lit(stride)) == 0).select("key")


def choose_pivots(sample: DataFrame, partitions: int, cap: int = 1_000_000) -> list:
    """Evenly spaced pivots of the sorted sample, at the driver; the sample's size is checked.

    A key that fills several partitions is a pivot several times, so there are always ``partitions`` - 1 pivots
    (none for an empty sample).
    """
    keys = gather(sample.sort("key"), cap).column("key").to_pylist()
    return [keys[len(keys) * i // partitions] for i in range(1, partitions)] if keys else []
