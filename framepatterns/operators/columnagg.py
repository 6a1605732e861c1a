"""Globally-reduce operators: column aggregates, length, equality."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from framepatterns.operators.aggregates import aggregate


def column_agg(df: DataFrame, aggs: dict[str, tuple]) -> DataFrame:
    """One row; ``aggs`` maps an output name to (column, aggregate)."""
    return df.agg(*[aggregate(h, F.col(c) if isinstance(c, str) else c).alias(n) for n, (c, h) in aggs.items()])


def pair_agg(df: DataFrame, a: str, b: str) -> DataFrame:
    """Sample covariance and correlation of two columns."""
    return df.agg(F.covar_samp(a, b).alias("cov"), F.corr(a, b).alias("corr"))


def describe(df: DataFrame, cols: list[str]) -> DataFrame:
    """One row a column: count, mean, std, min, quartiles, max; all columns in one pass."""
    stats = [F.struct(F.lit(c).alias("column"), F.count(c).alias("count"), F.avg(c).alias("mean"), F.stddev_samp(c).alias("std"), F.min(F.col(c).cast("double")).alias("min"), F.percentile_approx(F.col(c).cast("double"), [0.25, 0.5, 0.75]).alias("quartiles"), F.max(F.col(c).cast("double")).alias("max")) for c in cols]
    return df.agg(F.array(*stats).alias("s")).select(F.inline("s"))


def length(df: DataFrame) -> int:
    return df.count()


def _digest(df: DataFrame) -> Column:
    h = F.xxhash64(*df.columns)
    return F.struct(F.count("*").alias("n"), F.bit_xor(h).alias("x"), F.sum(F.pmod(h, F.lit(1 << 40)).cast("decimal(38,0)")).alias("s"))


def frames_equal(a: DataFrame, b: DataFrame, exact: bool = True) -> bool:
    """Whether two frames hold the same rows, in any order: row hashes first, then, if asked, row by row."""
    if [t for _, t in a.dtypes] != [t for _, t in b.dtypes]:
        return False
    if a.agg(_digest(a).alias("d")).first() != b.agg(_digest(b).alias("d")).first():
        return False
    return not exact or (a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty())


def frames_equal_ordered(a: DataFrame, b: DataFrame, order: list) -> bool:
    """Whether two frames are equal row by row in the order of ``order``."""
    from framepatterns.layout.rebalance import with_position

    x, y = with_position(a, order, "_p"), with_position(b, order, "_p")
    return frames_equal(x, y)
