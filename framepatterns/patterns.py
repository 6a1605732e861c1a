"""The parallel execution patterns.  Operators are instances of these; each says where rows are before and after."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import replace

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from framepatterns.collectives import all_reduce, broadcast_frame, halo_exchange, reduce, shuffle_by_key
from framepatterns.layout.hashing import hash_pid, local_bucket
from framepatterns.layout.ranges import histogram_pivots, key_struct, quantile_pivots, range_pid, spread_pid
from framepatterns.layout.rebalance import _columns, merge_runs, pivot_literal, positioned, with_position
from framepatterns.layout.sampling import choose_pivots, regular_sample
from framepatterns.model import Arbitrary, Frame, Hashed, Ordered, whole_input


def as_frame(x: Frame | DataFrame) -> Frame:
    return x if isinstance(x, Frame) else Frame(x)


def row_local(x: Frame | DataFrame, fn: Callable[[DataFrame], DataFrame]) -> Frame:
    """Local operator without communication: partitions and order stay as they are."""
    f = as_frame(x)
    return f.with_df(fn(f.df), note="row-local: no communication")


def local_kernel(x: Frame | DataFrame, fn: Callable[[pa.Table], pa.Table], schema) -> Frame:
    """Any serial function on Arrow data, batch by batch in every partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield from fn(pa.Table.from_batches([b])).to_batches()

    f = as_frame(x)
    return f.with_df(f.df.mapInArrow(run, schema), note="row-local: serial kernel on Arrow batches")


def shuffle_compute(frames: list, keys: list[str], op: Callable[..., DataFrame], partitions: int, local_buckets: int = 0, oversplit: int = 1) -> Frame:
    """Deal all frames by key hash, then the local operator.

    A frame that is already dealt so is not moved again.  ``oversplit`` deals to that many times more, smaller
    partitions from the start; ``local_buckets`` adds a bucket column by a second hash, for local operators
    that work bucket by bucket.
    """
    n, notes, dealt = partitions * oversplit, [], []
    for f in map(as_frame, frames):
        if f.layout == Hashed(tuple(keys), n):
            notes.append("shuffle-compute: input already dealt by key, not moved")
            df = f.df
        else:
            notes.append(f"shuffle-compute: all rows dealt by {', '.join(keys)} to {n} partitions")
            df = shuffle_by_key(f.df, keys, n)
        dealt.append(df.withColumn("_bucket", local_bucket(keys, local_buckets)) if local_buckets else df)
    return Frame(op(*dealt), layout=Hashed(tuple(keys), n), why=tuple(notes))


def combine_shuffle_reduce(x: Frame | DataFrame, keys: list[str], aggs: list[Column]) -> Frame:
    """Partial aggregates in every partition, only those are dealt by key, final aggregates there."""
    f = as_frame(x)
    return f.with_df(f.df.groupBy(*keys).agg(*aggs), Arbitrary(), f"combine-shuffle-reduce: partial aggregates dealt by {', '.join(keys)}")


def broadcast_compute(big: Frame | DataFrame, small: Frame | DataFrame, op: Callable[[DataFrame, DataFrame], DataFrame]) -> Frame:
    """Replicate the smaller frame (its size is checked), local operator; the bigger one does not move."""
    b, s = as_frame(big), as_frame(small)
    return b.with_df(op(b.df, broadcast_frame(s.df)), note="broadcast-compute: small side replicated")


def global_reduce(x: Frame | DataFrame, *aggs: Column, replicate: bool = False) -> DataFrame:
    """Local reduction, all-reduce, final value: one row, or the value in every row."""
    df = as_frame(x).df
    return all_reduce(df, *aggs) if replicate else reduce(df, *aggs)


def _dealt_in_order(df: DataFrame, below: Column, upto: Column, n: int, order: list[Column], hot: bool) -> DataFrame:
    """Deal rows by their range and merge what every partition receives.

    Where a pivot's key fills half a partition or more (``hot``), rows that equal pivots fill all partitions that
    may hold them.  Then every
    partition is sorted first, by all columns that can be ordered, and a row's place says to which of several
    partitions it goes: rows that tie there are equal, so a task that runs again sends the same rows.
    """
    if not hot:
        return merge_runs(df.withColumn("_to", upto.cast("int")).repartitionById(n, F.col("_to")).drop("_to"), order)
    rest = [F.col(c) for c, t in df.dtypes if not any(x in t for x in ("map<", "variant", "interval"))]
    placed = df.withColumns({"_below": below, "_upto": upto}).sortWithinPartitions(*order, *rest).withColumn("_i", F.monotonically_increasing_id())
    dealt = placed.withColumn("_to", spread_pid(F.col("_below"), F.col("_upto"), F.xxhash64("_i")))
    return merge_runs(dealt.repartitionById(n, F.col("_to")).drop("_below", "_upto", "_i", "_to"), order)


def order_by_range(x: Frame | DataFrame, key: str, partitions: int, bins: int = 1024, ascending: bool = True, sketch: bool = True) -> Frame:
    """Global order on one numeric key: pivots by quantile sketch (or by histogram), deal by range, local sort.  Nulls come last.

    Both kinds of pivots follow the rows, not the range of values: outliers and hot keys leave partitions even.
    """
    f = as_frame(x)
    whole_input(f.df, "a global sort")
    fine = FINER * partitions
    pivots, hot = _every(quantile_pivots(f.df, key, fine) if sketch else histogram_pivots(f.df, key, fine, bins))
    return deal_by_pivots(f, Ordered((key,), tuple(pivots), len(pivots) + 1, hot=hot), ascending, "quantile sketch" if sketch else "histogram")


#: Cuts that are looked at for each partition, to see which pivots stand in a crowded key.
FINER = 4


def _every(grid: list) -> tuple[list, bool]:
    """Every FINER-th cut as pivots, and whether one of them has equals on both sides: a key that fills half a partition."""
    at = range(FINER - 1, len(grid), FINER)
    return [grid[i] for i in at], any(grid[i - 1] == grid[i] == grid[i + 1] for i in at)


def deal_by_pivots(x: Frame | DataFrame, layout: Ordered, ascending: bool = True, how: str = "earlier") -> Frame:
    """Deal a frame by the pivots of an ordered layout, so that frames ordered alike can be merged without looking at their rows again."""
    f, n, pivots = as_frame(x), layout.partitions, list(layout.pivots)
    hot = layout.hot or len(set(pivots)) < len(pivots)
    if len(layout.keys) == 1 and all(isinstance(p, float) for p in pivots):
        key = layout.keys[0]
        below, upto = (F.when(F.col(key).isNull(), n - 1).otherwise(range_pid(F.col(key).cast("double"), pivots, F.lit, strict)) for strict in (True, False))
        if not ascending:
            below, upto = (F.when(F.col(key).isNull(), n - 1).otherwise(n - 1 - b) for b in (upto, below))
        order = F.col(key).asc_nulls_last() if ascending else F.col(key).desc_nulls_last()
        out = _dealt_in_order(f.df, below, upto, n, [order], hot)
        return f.with_df(out, replace(layout, ascending=ascending), f"globally ordered: range partition by {n - 1} pivots ({how})")
    cols = [F.col(k) for k in layout.keys]
    literal, key = pivot_literal(f.df, cols), key_struct(cols)
    below, upto = (range_pid(key, pivots, literal, strict) for strict in (True, False))
    return f.with_df(_dealt_in_order(f.df, below, upto, n, cols, hot), layout, f"globally ordered: sample sort with {n - 1} pivots ({how})")


def order_by_sample(x: Frame | DataFrame, keys: list, partitions: int, per_partition: int = 64) -> Frame:
    """Global order on several keys: sort locally, take a regular sample, choose pivots at one place, split, deal, merge.

    ``keys`` are columns by name (nulls first).  A key that fills several partitions is spread over them.
    """
    f = as_frame(x)
    whole_input(f.df, "a global sort")
    pivots, hot = _every(choose_pivots(regular_sample(f.df, _columns(keys), per_partition), FINER * partitions))
    layout = Ordered(tuple(keys), tuple(tuple(p.values()) for p in pivots), len(pivots) + 1, hot=hot)
    return deal_by_pivots(f, layout, how="regular sample")


def halo(x: Frame | DataFrame, order: list, back: int, ahead: int, op: Callable[[DataFrame], DataFrame], block: int = 1 << 16) -> Frame:
    """Global order, then the neighbours' edge rows, then a local operator on every block.

    Rows are numbered in ``order`` and cut into blocks of ``block`` positions; each block receives copies of the
    ``back`` rows before it and the ``ahead`` rows after it, from as many neighbours as hold them.  ``op`` sees
    the columns _at (position) and _block, and its results for copies are dropped.
    """
    f = as_frame(x)
    placed, total = positioned(f.df, order, "_at")
    block = max(block, 10 * max(back, ahead, 1))
    near = halo_exchange(placed, "_at", back, ahead, block, total)
    out = op(near).where("_home").drop("_block", "_home", "_at")
    return f.with_df(out, Arbitrary(), f"globally ordered with halos: blocks of {block} rows, {back} before and {ahead} after")


def transpose_compute(x: Frame | DataFrame, index: str, op: Callable[[Column], Column] | None = None, block: int = 4096) -> Frame:
    """Cut the rows into blocks, turn every block in place, then bring the pieces of a column together.

    Gives (column, block, values): one row for each column and block of ``block`` rows in the order of
    ``index``, so a result with as many columns as the input has rows stays distributed.  ``op`` is applied to
    every piece before the pieces travel.  All columns but ``index`` have one type.
    """
    f = as_frame(x)
    columns = [c for c in f.df.columns if c != index]
    placed = with_position(f.df, [index], "_at").withColumn("block", F.floor(F.col("_at") / block))
    turned = placed.groupBy("block").agg(*[F.array_sort(F.collect_list(F.struct("_at", F.col(c).alias("value")))).alias(c) for c in columns])
    pieces = turned.unpivot(["block"], columns, "column", "cells").withColumn("values", F.transform("cells", lambda v: v["value"]))
    values = op(F.col("values")) if op else F.col("values")
    return f.with_df(pieces.select("column", "block", values.alias("values")), Arbitrary(), f"transpose-compute: blocks of {block} rows turned in place")


def partition_ids(keys: list[str], partitions: int) -> Column:
    return hash_pid(keys, partitions)
