"""Lengths, global positions and rebalancing.

Positions never depend on how an earlier pass dealt the rows: partitions are those of explicit pivots, which
are functions of the row.
"""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from framepatterns.collectives import shuffle
from framepatterns.layout.ranges import key_struct, range_pid
from framepatterns.layout.sampling import choose_pivots, regular_sample
from framepatterns.model import whole_input


def partition_lengths(df: DataFrame) -> list[int]:
    """Rows of every partition as it is dealt now; the driver holds P numbers."""
    found = dict(df.groupBy(F.spark_partition_id().alias("p")).count().collect())
    return [found.get(i, 0) for i in range(max(found, default=-1) + 1)]


def _columns(order: list) -> list[Column]:
    return [F.col(c) if isinstance(c, str) else c for c in order]


def pivot_literal(df: DataFrame, cols: list[Column]):
    """A function that writes a pivot (a tuple or a row of values) as a comparable key of the types of ``cols``."""
    types = [f.dataType for f in df.select(*[c.alias(f"k{i}") for i, c in enumerate(cols)]).schema]

    def literal(p) -> Column:
        values = p.values() if isinstance(p, dict) else p
        return F.struct(*[F.lit(v).cast(t).alias(f"k{i}") for i, (v, t) in enumerate(zip(values, types, strict=True))])

    return literal


def tie_hash(df: DataFrame) -> Column:
    """A hash of the whole row, to order rows that are equal in the columns asked for; equal rows are interchangeable."""
    known = [c for c, t in df.dtypes if not any(x in t for x in ("map<", "variant"))]
    return F.xxhash64(*known) if known else F.lit(0).cast("long")


def ordered_ids(df: DataFrame, order: list, partitions: int, per_partition: int = 64) -> tuple[Column, int, Column]:
    """A partition id that keeps the order of ``order``, as a function of the row; the number of partitions; the tie.

    Rows that are equal in ``order`` are told apart by ``tie_hash``, so a hot key does not fill one partition.
    """
    tie = tie_hash(whole_input(df, "a global order"))
    cols = [*_columns(order), tie]
    pivots = choose_pivots(regular_sample(df, cols, per_partition), partitions)
    return range_pid(key_struct(cols), pivots, pivot_literal(df, cols)), len(pivots) + 1, tie


def positioned(df: DataFrame, order: list, name: str = "position", partitions: int | None = None) -> tuple[DataFrame, int]:
    """``df`` with the global position of every row in ``order`` (ties by a hash of the row), and the number of rows.

    Rows are dealt by pivots, numbered in their partition, and shifted by the lengths of earlier partitions.
    """
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    pid, n, tie = ordered_ids(df, order, n)
    dealt = df.withColumns({"_pid": pid, "_tie": tie})
    lengths = dict(dealt.groupBy("_pid").count().collect())
    offsets = [0, *accumulate(lengths.get(i, 0) for i in range(n))]
    placed = shuffle(dealt, F.col("_pid"), n)
    own = F.row_number().over(W.Window.partitionBy("_pid").orderBy(*_columns(order), "_tie"))
    shift = F.element_at(F.array(*[F.lit(o).cast("long") for o in offsets[:n]]), F.col("_pid") + 1)
    return placed.withColumn(name, (shift + own - 1).cast("long")).drop("_pid", "_tie"), offsets[-1]


def with_position(df: DataFrame, order: list, name: str = "position", partitions: int | None = None) -> DataFrame:
    """Number the rows from 0 in the order of ``order``, without a window over all rows."""
    return positioned(df, order, name, partitions)[0]


def rebalance(df: DataFrame, order: list, partitions: int | None = None, lengths: list[int] | None = None) -> DataFrame:
    """Deal rows in order into equal partitions, or into partitions of the given lengths."""
    placed, total = positioned(df, order, "_at")
    if lengths is None:
        partitions = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        pid = F.least(F.floor(F.col("_at") * partitions / max(total, 1)), F.lit(partitions - 1)).cast("int")
    else:
        if sum(lengths) != total:
            raise ValueError(f"lengths add up to {sum(lengths)}, the frame has {total} rows")
        partitions = len(lengths)
        pid = range_pid(F.col("_at"), list(accumulate(lengths))[:-1], F.lit)
    return shuffle(placed, pid, partitions).sortWithinPartitions("_at").drop("_at")


def weighted_pid(df: DataFrame, weight: str, order: list, partitions: int) -> DataFrame:
    """Add ``pid`` so that partitions hold neighbouring rows of about equal total weight."""
    pid, n, tie = ordered_ids(df, order, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    dealt = df.withColumns({"_pid": pid, "_tie": tie})
    sums = dict(dealt.groupBy("_pid").agg(F.sum(F.coalesce(F.col(weight), F.lit(0)))).collect())
    offsets = [0, *accumulate(sums.get(i, 0) or 0 for i in range(n))]
    shift = F.element_at(F.array(*[F.lit(o).cast("long") for o in offsets[:n]]), F.col("_pid") + 1)
    upto = W.Window.partitionBy("_pid").orderBy(*_columns(order), "_tie").rowsBetween(W.Window.unboundedPreceding, -1)
    before = shift + F.coalesce(F.sum(F.coalesce(F.col(weight), F.lit(0))).over(upto), F.lit(0))
    out = shuffle(dealt, F.col("_pid"), n).withColumn("pid", F.least(F.floor(before * partitions / max(offsets[-1], 1)), F.lit(partitions - 1)).cast("int"))
    return out.drop("_pid", "_tie")


def merge_runs(df: DataFrame, keys: list) -> DataFrame:
    """One ordered run a partition from the sorted runs that it received: the local sort finds them and merges."""
    return df.sortWithinPartitions(*_columns(keys))
