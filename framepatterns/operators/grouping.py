"""Group-by and unique, in the combine-first and in the shuffle-first form, chosen by cardinality where asked."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from framepatterns.operators.aggregates import Partial, aggregate, classify
from framepatterns.patterns import Frame, as_frame, combine_shuffle_reduce, shuffle_compute
from framepatterns.plans.choose import PatternChoice, choose_group_pattern


def groupby(x: Frame | DataFrame, keys: list[str], aggs: dict[str, tuple], pattern: str = "auto", partitions: int | None = None, null_keys: str = "group", label: Column | None = None, salt: int = 0) -> Frame:
    """Group ``x`` by ``keys``; ``aggs`` maps an output name to (column, aggregate).

    pattern: "combine" (partial aggregates first), "shuffle" (rows first), or "auto" (by measured combine
    ratio and aggregate class).  null_keys "drop" leaves out rows with a null key.  ``salt`` splits hot keys in
    the shuffle form by a first aggregation per (key, salt); it needs distributive aggregates.
    """
    f = as_frame(x)
    df = f.df if null_keys == "group" else f.df.dropna(subset=keys)
    hows = [h for _, h in aggs.values()]
    exprs = [aggregate(h, F.col(c) if isinstance(c, str) else c, label).alias(name) for name, (c, h) in aggs.items()]
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    choice = PatternChoice(pattern, "asked for") if pattern != "auto" else choose_group_pattern(df, keys, classify(hows))
    if salt:
        return f.with_df(_salted(df, keys, aggs, salt), note=f"combine-shuffle-reduce with {salt} salts")
    if choice.pattern == "combine":
        out = combine_shuffle_reduce(df, keys, exprs)
    else:
        out = shuffle_compute([Frame(df, layout=f.layout)], keys, lambda d: d.groupBy(*keys).agg(*exprs), n)
    return out.with_df(out.df, note=f"choice: {choice.pattern} ({choice.reason})")


_AGAIN = {"count": F.sum, "size": F.sum, "sum": F.sum, "min": F.min, "max": F.max, "any": F.bool_or, "all": F.bool_and, "prod": F.product}


def _salted(df: DataFrame, keys: list[str], aggs: dict[str, tuple], salt: int) -> DataFrame:
    wrong = [h for _, h in aggs.values() if isinstance(h, Partial) or h not in _AGAIN]
    if wrong:
        raise ValueError(f"salting needs distributive aggregates, not {wrong}")
    part = df.withColumn("_salt", F.pmod(F.xxhash64(*df.columns), F.lit(salt))).groupBy(*keys, "_salt").agg(*[aggregate(h, F.col(c) if isinstance(c, str) else c).alias(n) for n, (c, h) in aggs.items()])
    return part.groupBy(*keys).agg(*[_AGAIN[h](n).alias(n) for n, (_, h) in aggs.items()])


def group_transform(df: DataFrame, keys: list[str], exprs: dict[str, Column]) -> DataFrame:
    """Aggregates of the group in every row: aggregate first, then join back, so a hot group never sits in one window."""
    stats = df.groupBy(*keys).agg(*[e.alias(n) for n, e in exprs.items()])
    right = stats.toDF(*[f"_{k}" for k in keys], *exprs)
    return df.join(right, [df[k].eqNullSafe(right[f"_{k}"]) for k in keys], "left").drop(*[f"_{k}" for k in keys])


def group_filter(df: DataFrame, keys: list[str], condition: Column) -> DataFrame:
    """Rows of the groups whose aggregates meet the condition."""
    kept = df.groupBy(*keys).agg(condition.alias("_keep")).where("_keep").select(*[F.col(k).alias(f"_{k}") for k in keys])
    return df.join(kept, [df[k].eqNullSafe(kept[f"_{k}"]) for k in keys], "left_semi")


def group_apply(df: DataFrame, keys: list[str], fn: Callable, schema: str) -> DataFrame:
    """An opaque function on each group's Arrow table; each group must fit into one task."""
    return df.groupBy(*keys).applyInArrow(fn, schema)


def unique(x: Frame | DataFrame, subset: list[str] | None = None, keep: str = "any", label: str | None = None, pattern: str = "combine", partitions: int | None = None) -> Frame:
    """One row for each distinct value of ``subset`` (all columns).

    keep: "any"; "first" and "last" by ``label`` (unique within the value); "none" keeps only values that
    occur once.  pattern "shuffle" deals the rows by value before looking for repeats.
    """
    f = as_frame(x)
    df, cols = f.df, subset or f.df.columns
    if keep == "any":
        if pattern == "shuffle":
            n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
            return shuffle_compute([f], cols, lambda d: d.dropDuplicates(cols), n)
        return f.with_df(df.dropDuplicates(cols), note="combine-shuffle-reduce: repeats dropped before and after the shuffle")
    if keep == "none":
        once = df.groupBy(*cols).agg(F.count("*").alias("_n"), *[F.first(c).alias(c) for c in df.columns if c not in cols]).where("_n = 1")
        return f.with_df(once.select(*df.columns), note="combine-shuffle-reduce: values that occur once")
    if label is None:
        raise ValueError("first and last need a label")
    pick = (F.min_by if keep == "first" else F.max_by)(F.struct(*df.columns), F.col(label))
    return f.with_df(df.groupBy(*[F.col(c).alias(f"_k{i}") for i, c in enumerate(cols)]).agg(pick.alias("r")).select("r.*"), note=f"combine-shuffle-reduce: {keep} by {label}")


def duplicated(df: DataFrame, subset: list[str], label: str) -> DataFrame:
    """``df`` with a flag: an earlier row (by ``label``) has the same values."""
    return df.withColumn("duplicated", F.row_number().over(W.Window.partitionBy(*subset).orderBy(label)) > 1)
