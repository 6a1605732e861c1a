"""Joins: shuffle, broadcast, adaptive, salted, theta, range and as-of."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from framepatterns.collectives import broadcast_frame
from framepatterns.layout.ranges import quantile_pivots, range_pid
from framepatterns.model import Arbitrary
from framepatterns.patterns import Frame, as_frame, broadcast_compute, shuffle_compute
from framepatterns.plans.choose import broadcast_side, choose_join_pattern

HINTS = {"sort": "MERGE", "hash": "SHUFFLE_HASH", "auto": None}


def _on(l: DataFrame, r: DataFrame, on: list, null_keys: str) -> tuple[DataFrame, DataFrame, list[str] | Column]:
    pairs = [(k, k) if isinstance(k, str) else k for k in on]
    if null_keys == "never" and all(a == b for a, b in pairs):
        return l, r, [a for a, _ in pairs]
    r = r.withColumnsRenamed({b: f"_r_{b}" for _, b in pairs})
    cond = F.lit(True)
    for a, b in pairs:
        cond = cond & (l[a].eqNullSafe(r[f"_r_{b}"]) if null_keys == "match" else l[a] == r[f"_r_{b}"])
    return l, r, cond


def _suffixed(l: DataFrame, r: DataFrame, on: list, suffixes: tuple[str, str]) -> tuple[DataFrame, DataFrame]:
    keys_l = [k if isinstance(k, str) else k[0] for k in on]
    keys_r = [k if isinstance(k, str) else k[1] for k in on]
    both = (set(l.columns) - set(keys_l)) & (set(r.columns) - set(keys_r))
    return l.withColumnsRenamed({c: c + suffixes[0] for c in both}), r.withColumnsRenamed({c: c + suffixes[1] for c in both})


def join(left, right, on: list, how: str = "inner", algorithm: str = "auto", null_keys: str = "never", suffixes: tuple[str, str] = ("_x", "_y"), partitions: int | None = None, skew: str | None = None) -> Frame:
    """Shuffle join.  ``on`` lists names, or pairs of names where the sides differ.

    The local algorithm is "sort" or "hash".  With ``partitions``, both sides are dealt explicitly and a side
    that is already dealt so stays where it is.  skew "salt" splits the left side's heavy keys.
    """
    l, r = as_frame(left), as_frame(right)
    if skew == "salt":
        return Frame(salted_join(l.df, r.df, on, how), why=("shuffle-compute: heavy keys salted",))
    a, b = _suffixed(l.df, r.df, on, suffixes)
    if partitions and null_keys == "never" and all(isinstance(k, str) for k in on):
        return shuffle_compute([l.with_df(a), r.with_df(b)], list(on), lambda x, y: x.join(y, list(on), how), partitions)
    a, b, cond = _on(a, b, on, null_keys)
    b = b.hint(HINTS[algorithm]) if HINTS[algorithm] else b
    out = a.join(b, cond, how)
    drop = [c for c in out.columns if c.startswith("_r_")]
    if how in ("right", "outer", "full"):
        for k in on:
            x, y = (k, k) if isinstance(k, str) else k
            if f"_r_{y}" in drop:
                out = out.withColumn(x, F.coalesce(F.col(x), F.col(f"_r_{y}")))
    return Frame(out.drop(*drop), why=(f"shuffle-compute: {how} join",))


def broadcast_join(big, small, on, how: str = "inner") -> Frame:
    """Replicate the right side.  Refused where the right side's unmatched rows must be kept.  ``on`` may be a condition."""
    if broadcast_side(how) != "right":
        raise ValueError(f"a {how} join must not replicate its right side; use the shuffle join")
    return broadcast_compute(big, small, lambda x, y: x.join(y, on, how))


def join_auto(left, right, on: list, how: str = "inner") -> Frame:
    """Broadcast (of either side) or shuffle, by estimated sizes and by what ``how`` allows."""
    l, r = as_frame(left), as_frame(right)
    choice = choose_join_pattern(l.df, r.df, how)
    if choice.pattern != "broadcast":
        out = join(l, r, on, how)
    elif choice.side == "right":
        out = broadcast_join(l, r, list(on), how)
    else:
        small = broadcast_frame(l.df)
        out = r.with_df(small.join(r.df, list(on), how), Arbitrary(), "broadcast-compute: left side replicated")
    return out.with_df(out.df, note=f"choice: {choice.pattern} ({choice.reason})")


def heavy_keys(df: DataFrame, keys: list[str], share: float = 0.001) -> DataFrame:
    """Keys with more than ``share`` of all rows: at most 1/share of them, counted with partial aggregation."""
    counts = df.groupBy(*keys).agg(F.count("*").alias("_n"))
    total = df.count()
    return counts.where(F.col("_n") > max(1, share * total)).select(*keys)


def salted_join(left: DataFrame, right: DataFrame, on: list[str], how: str = "inner", salts: int = 16, share: float = 0.001) -> DataFrame:
    """Split the heavy keys of the left side over ``salts`` partitions; the right side's rows of those keys are copied."""
    if how not in ("inner", "left", "left_semi", "left_anti"):
        raise ValueError("salting keeps unmatched rows of the left side only")
    heavy = F.broadcast(heavy_keys(left, on, share).withColumn("_heavy", F.lit(True)))
    spread = F.when(F.col("_heavy"), F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int")).otherwise(0)
    l = left.join(heavy, on, "left").withColumn("_salt", spread).drop("_heavy")
    r = right.join(heavy, on, "left").withColumn("_salt", F.explode(F.when(F.col("_heavy"), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0))))).drop("_heavy")
    return l.join(r, [*on, "_salt"], how).drop("_salt")


def theta_join(big: DataFrame, small: DataFrame, condition: Column, how: str = "inner") -> DataFrame:
    """Any condition, by nested loops over the replicated (checked) small side."""
    return big.join(broadcast_frame(small), condition, how)


def range_join(points: DataFrame, at: str, intervals: DataFrame, low: str, high: str, width: float) -> DataFrame:
    """Points with the half-open intervals [low, high) that hold them.

    Both sides meet in buckets of ``width``: an interval is copied to the buckets it touches, so the join is
    an equi-join and no pair outside a common bucket is looked at.
    """
    p = points.withColumn("_b", F.floor(F.col(at) / width))
    i = intervals.withColumn("_b", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return p.join(i, "_b").where((F.col(at) >= F.col(low)) & (F.col(at) < F.col(high))).drop("_b")


def asof_join(left: DataFrame, right: DataFrame, by: list[str], at: str, take: list[str], tie: str | None = None, slices: int | None = None) -> DataFrame:
    """Each left row with the columns ``take`` of the last right row at or before it in its group.

    Both sides are stacked and a window carries the last right row forward, so nothing is multiplied.  Time is
    cut into ``slices`` by quantiles of the right side (default: the shuffle partitions), and every slice of a
    group starts with the last right row of the slices before it, so a hot group is not one task.  At equal
    ``at``, right rows come first; of several the largest ``tie`` counts.
    """
    value = F.struct(*[F.col(c).alias(c) for c in take])
    empty = F.lit(None).cast(right.select(value.alias("v")).schema["v"].dataType)
    rest = [c for c in left.columns if c not in (*by, at)]
    l = left.select(*by, at, F.lit(1).alias("_side"), F.struct(*rest).alias("_row"), empty.alias("_v"), F.lit(0).cast("long").alias("_t"))
    none = F.lit(None).cast(l.schema["_row"].dataType)
    r = right.select(*by, at, F.lit(0).alias("_side"), none.alias("_row"), value.alias("_v"), (F.col(tie).cast("long") if tie else F.lit(0).cast("long")).alias("_t"))
    place = lambda df: df.withColumn("_x", (F.col(at).cast("timestamp") if dict(df.dtypes)[at] in ("timestamp_ntz", "date") else F.col(at)).cast("double"))
    n = int(left.sparkSession.conf.get("spark.sql.shuffle.partitions")) if slices is None else slices
    pivots = sorted(set(quantile_pivots(place(right), "_x", n))) if n > 1 else []
    both = place(l.unionByName(r)).withColumn("_slice", F.coalesce(range_pid(F.col("_x"), pivots, F.lit), F.lit(0))).drop("_x")
    order = [F.col(at), F.col("_side"), F.col("_t")]
    upto = W.Window.partitionBy(*by, "_slice").orderBy(*order).rowsBetween(W.Window.unboundedPreceding, W.Window.currentRow)
    out = both.withColumn("_last", F.last("_v", ignorenulls=True).over(upto))
    if pivots:
        ends = both.groupBy(*by, "_slice").agg(F.max_by("_v", F.when(F.col("_side") == 0, F.struct(at, "_t"))).alias("_end"))
        before = W.Window.partitionBy(*by).orderBy("_slice").rowsBetween(W.Window.unboundedPreceding, -1)
        carried = ends.select(*[F.col(k).alias(f"_g{i}") for i, k in enumerate(by)], F.col("_slice").alias("_s"), F.last("_end", ignorenulls=True).over(before).alias("_carried"))
        same = [out[k].eqNullSafe(carried[f"_g{i}"]) for i, k in enumerate(by)]
        out = out.where("_side = 1").join(carried, [*same, out["_slice"] == carried["_s"]]).withColumn("_last", F.coalesce("_last", "_carried"))
    return out.where("_side = 1").select(*by, at, "_row.*", *[F.col(f"_last.{c}").alias(f"asof_{c}") for c in take])
