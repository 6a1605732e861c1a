"""Windows over a globally ordered frame without a key: halo exchange.

Rows are numbered and cut into blocks of positions.  A rolling window needs the last rows of the blocks before
it, so those rows are copied there (several blocks where the window is longer than a block); an expanding
window needs only the aggregate of everything before its block, so blocks exchange one partial state each.
"""

from __future__ import annotations

import operator
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import window as W

from framepatterns.layout.rebalance import positioned
from framepatterns.patterns import halo


def rolling(df: DataFrame, order: list, k: int, aggs: dict[str, Callable[[], Column]], keys: list[str] | None = None, min_periods: int | None = None, center: bool = False, block: int = 1 << 16) -> DataFrame:
    """The last k rows (or k centred rows) up to each row; null where fewer than ``min_periods`` rows are there.

    With ``keys`` each key has its own order, which Spark's windows do directly.  Without, blocks of at least
    ten windows' length exchange halos.
    """
    back, ahead = (k // 2, (k - 1) // 2) if center else (k - 1, 0)
    least = k if min_periods is None else min_periods
    if keys:
        return _rolled(df, W.Window.partitionBy(*keys).orderBy(*order).rowsBetween(-back, ahead), aggs, least)
    w = W.Window.partitionBy("_block").orderBy("_at").rowsBetween(-back, ahead)
    return halo(df, order, back, ahead, lambda near: _rolled(near, w, aggs, least), block).df


def _rolled(src: DataFrame, w, aggs: dict[str, Callable[[], Column]], least: int) -> DataFrame:
    out = src.withColumn("_n", F.count("*").over(w)).withColumns({n: f().over(w) for n, f in aggs.items()})
    return out.withColumns({n: F.when(F.col("_n") >= least, F.col(n)) for n in aggs}).drop("_n")


def rolling_time(df: DataFrame, ts: str, micros: int, aggs: dict[str, Callable[[], Column]], keys: list[str] | None = None, closed: str = "right", bucket_micros: int | None = None) -> DataFrame:
    """Rows within ``micros`` before each row's time; closed: right (t-d, t], left [t-d, t), both, neither.

    Without keys, time is cut into buckets and each row is copied to the following buckets that its reach meets.
    """
    lo, hi = {"right": (-micros + 1, 0), "left": (-micros, -1), "both": (-micros, 0), "neither": (-micros + 1, -1)}[closed]
    at = df.withColumn("_us", F.unix_micros(F.col(ts).cast("timestamp")))
    if keys:
        w = W.Window.partitionBy(*keys).orderBy("_us").rangeBetween(lo, hi)
        return at.withColumns({n: f().over(w) for n, f in aggs.items()}).drop("_us")
    size = bucket_micros or 10 * micros
    reach = F.sequence(F.floor(F.col("_us") / size), F.floor((F.col("_us") + micros) / size))
    copies = at.withColumn("_b", F.explode(reach)).withColumn("_home", F.col("_b") == F.floor(F.col("_us") / size))
    w = W.Window.partitionBy("_b").orderBy("_us").rangeBetween(lo, hi)
    return copies.withColumns({n: f().over(w) for n, f in aggs.items()}).where("_home").drop("_us", "_b", "_home")


MAX_BLOCKS = 4096


def _either(fn: Callable) -> Callable:
    return lambda a, b: b if a is None else a if b is None else fn(a, b)


def _low(a, b):
    return b if a != a else a if b != b else min(a, b)  # NaN counts as the largest number, as in Spark


def _high(a, b):
    return a if a != a else b if b != b else max(a, b)


_ADD = {"sum": _either(operator.add), "count": _either(operator.add), "min": _either(_low), "max": _either(_high), "prod": _either(operator.mul)}
_PART = {"sum": F.sum, "count": F.count, "min": F.min, "max": F.max, "prod": F.product}


def expanding(df: DataFrame, order: list, aggs: dict[str, tuple[str, str]], min_periods: int = 1, block: int = 1 << 16) -> DataFrame:
    """Aggregates of all rows up to each row; ``aggs`` maps a name to (column, sum | count | min | max | prod | mean).

    Blocks grow with the frame so that there are at most MAX_BLOCKS; the driver adds up their states.
    """
    parts = {f"_{n}_{p}": (c, p) for n, (c, h) in aggs.items() for p in (("sum", "count") if h == "mean" else (h,))}
    placed, total = positioned(df, order, "_at")
    block = max(block, -(-total // MAX_BLOCKS))
    placed = placed.withColumn("_block", F.floor(F.col("_at") / block))
    states = placed.groupBy("_block").agg(*[_PART[p](c).alias(n) for n, (c, p) in parts.items()])
    run: dict = dict.fromkeys(parts)
    before = []
    for row in sorted(states.collect(), key=lambda r: r["_block"]):
        before.append((row["_block"], *run.values()))
        run = {n: _ADD[p](run[n], row[n]) for n, (_, p) in parts.items()}
    schema = T.StructType([T.StructField("_block", T.LongType()), *[T.StructField(f"{n}_before", states.schema[n].dataType) for n in parts]])
    prefix = F.broadcast(df.sparkSession.createDataFrame(before, schema))
    w = W.Window.partitionBy("_block").orderBy("_at").rowsBetween(W.Window.unboundedPreceding, W.Window.currentRow)
    out = placed.join(prefix, "_block").withColumns({n: _PART[p](c).over(w) for n, (c, p) in parts.items()})

    def upto(n: str, p: str) -> Column:
        own, prev = F.col(n), F.col(f"{n}_before")
        if p in ("sum", "count"):
            return F.when(own.isNull() & prev.isNull(), None).otherwise(F.coalesce(own, F.lit(0)) + F.coalesce(prev, F.lit(0)))
        if p == "prod":
            return F.when(own.isNull() & prev.isNull(), None).otherwise(F.coalesce(own, F.lit(1.0)) * F.coalesce(prev, F.lit(1.0)))
        return (F.least if p == "min" else F.greatest)(own, prev)

    final = {n: upto(f"_{n}_sum", "sum") / upto(f"_{n}_count", "count") if h == "mean" else upto(f"_{n}_{h}", h) for n, (_, h) in aggs.items()}
    out = out.withColumns({n: F.when(F.col("_at") + 1 >= min_periods, e) for n, e in final.items()})
    return out.drop("_at", "_block", *parts, *[f"{n}_before" for n in parts])


def cumulate(df: DataFrame, order: list, col: str, how: str, name: str) -> DataFrame:
    return expanding(df, order, {name: (col, how)})


def shift(df: DataFrame, order: list, col: str, h: int, name: str, keys: list[str] | None = None, block: int = 1 << 16) -> DataFrame:
    """The value h rows before (h < 0: after)."""
    if keys:
        return df.withColumn(name, F.lag(col, h).over(W.Window.partitionBy(*keys).orderBy(*order)))
    w = W.Window.partitionBy("_block").orderBy("_at")
    return halo(df, order, max(h, 0), max(-h, 0), lambda near: near.withColumn(name, F.lag(col, h).over(w)), block).df


def diff(df: DataFrame, order: list, col: str, h: int, name: str, **more) -> DataFrame:
    out = shift(df, order, col, h, "_before", **more)
    return out.withColumn(name, F.col(col) - F.col("_before")).drop("_before")


def pct_change(df: DataFrame, order: list, col: str, h: int, name: str, **more) -> DataFrame:
    out = shift(df, order, col, h, "_before", **more)
    return out.withColumn(name, F.col(col) / F.col("_before") - 1).drop("_before")


def _filled(df: DataFrame, keys: list[str], order: list, col: str, name: str, forward: bool, limit: int | None) -> DataFrame:
    lo, hi = (W.Window.unboundedPreceding if limit is None else -limit, 0) if forward else (0, W.Window.unboundedFollowing if limit is None else limit)
    w = W.Window.partitionBy(*keys).orderBy(*order).rowsBetween(lo, hi)
    return df.withColumn(name, (F.last if forward else F.first)(col, ignorenulls=True).over(w))


def fill_forward(df: DataFrame, keys: list[str], order: list, col: str, name: str, limit: int | None = None) -> DataFrame:
    """Nulls replaced by the last value before them, by key; by one of the ``limit`` rows before only."""
    return _filled(df, keys, order, col, name, True, limit)


def fill_backward(df: DataFrame, keys: list[str], order: list, col: str, name: str, limit: int | None = None) -> DataFrame:
    """Nulls replaced by the next value after them, by key; by one of the ``limit`` rows after only."""
    return _filled(df, keys, order, col, name, False, limit)


def interpolate(df: DataFrame, keys: list[str], at: str, col: str, name: str) -> DataFrame:
    """Nulls between two values on the straight line through them, by key; ``at`` is the numeric place.

    Nulls after the last value take it; nulls before the first stay.
    """
    here = F.when(F.col(col).isNotNull(), F.struct(F.col(at).cast("double").alias("x"), F.col(col).cast("double").alias("y")))
    near = df.withColumn("_here", here)
    w = W.Window.partitionBy(*keys).orderBy(at)
    back, ahead = w.rowsBetween(W.Window.unboundedPreceding, 0), w.rowsBetween(0, W.Window.unboundedFollowing)
    near = near.withColumns({"_p": F.last("_here", ignorenulls=True).over(back), "_q": F.first("_here", ignorenulls=True).over(ahead)})
    line = F.col("_p.y") + (F.col("_q.y") - F.col("_p.y")) * (F.col(at) - F.col("_p.x")) / F.when(F.col("_q.x") != F.col("_p.x"), F.col("_q.x") - F.col("_p.x"))
    return near.withColumn(name, F.coalesce(F.col(col).cast("double"), line, F.col("_p.y"))).drop("_here", "_p", "_q")
