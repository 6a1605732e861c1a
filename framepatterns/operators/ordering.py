"""Sort and rank on the globally-ordered pattern."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from framepatterns.layout.rebalance import with_position
from framepatterns.operators.windows import expanding
from framepatterns.patterns import Frame, as_frame, order_by_range, order_by_sample


def sort(x, by: list[str], ascending: bool | list[bool] = True, algorithm: str = "auto", partitions: int | None = None, nulls: str = "last") -> Frame:
    """Global sort: "range" (one numeric key), "sample" (any keys), "native", or "auto".

    The first two take pivots from the rows' quantiles, so few, hot and outlying keys leave the partitions even.
    Mixed directions and null placement other than the samples' go to the native range sort.
    """
    f = as_frame(x)
    flags = [ascending] * len(by) if isinstance(ascending, bool) else list(ascending)
    numeric = len(by) == 1 and dict(f.df.dtypes)[by[0]] in ("tinyint", "smallint", "int", "bigint", "float", "double")
    n = partitions or int(f.df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    if algorithm == "auto":
        algorithm = "range" if numeric and nulls == "last" else "sample" if all(flags) and nulls == "first" else "native"
    if algorithm == "range":
        return order_by_range(f, by[0], n, ascending=flags[0])
    if algorithm == "sample":
        if not all(flags):
            raise ValueError("sample sort is ascending; negate numeric keys or use the native sort")
        return order_by_sample(f, by, n)
    cols = [getattr(F.col(c), ("asc" if a else "desc") + f"_nulls_{nulls}")() for c, a in zip(by, flags, strict=True)]
    return f.with_df(f.df.orderBy(*cols), note="globally ordered: native range sort")


def rank(df: DataFrame, by: list[str], method: str = "first", tie: list[str] | None = None, name: str = "rank", partitions: int | None = None) -> DataFrame:
    """Rank from 1 over the whole frame without a window over all rows.

    first: by position (``tie`` breaks ties); min: rows before plus one; max: rows up to the last equal one;
    average: the mean of the two; dense: distinct keys up to the row; pct: the average as a share of all rows.
    All but the first rank the distinct keys, with their counts, and join the ranks back, so the rows of a hot
    key are never brought together.
    """
    if method == "first":
        return with_position(df, [*by, *(tie or [])], "_p", partitions).withColumn(name, F.col("_p") + 1).drop("_p")
    keys = df.groupBy(*by).agg(F.count("*").alias("_n"))
    if method == "dense":
        ranked = with_position(keys, by, "_r", partitions).withColumn("_r", F.col("_r") + 1)
    elif method in ("min", "max", "average", "pct"):
        ranked, upto = expanding(keys, by, {"_upto": ("_n", "sum")}), F.col("_upto")
        low = upto - F.col("_n") + 1
        mean = (low + upto) / 2
        if method == "pct":
            ranked = ranked.join(F.broadcast(keys.agg(F.sum("_n").alias("_all"))), how="cross")
        ranked = ranked.withColumn("_r", {"min": low, "max": upto, "average": mean}[method] if method != "pct" else mean / F.col("_all"))
    else:
        raise ValueError(method)
    kind = "double" if method in ("average", "pct") else "long"
    ranked = ranked.select(*[F.col(c).alias(f"_k{i}") for i, c in enumerate(by)], F.col("_r").cast(kind).alias(name))
    same = [df[c].eqNullSafe(ranked[f"_k{i}"]) for i, c in enumerate(by)]
    return df.join(ranked, same).drop(*[f"_k{i}" for i in range(len(by))])


def top_k(df: DataFrame, k: int, by: list) -> DataFrame:
    """The first k rows in an order: k rows a partition travel, no sort of the whole frame."""
    return df.orderBy(*by).limit(k)


def top_k_per_key(df: DataFrame, k: int, keys: list[str], by: list) -> DataFrame:
    return df.withColumn("rn", F.row_number().over(W.Window.partitionBy(*keys).orderBy(*by))).where(F.col("rn") <= k)
