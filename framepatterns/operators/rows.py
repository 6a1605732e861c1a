"""Row-local operators: select, project, map, row aggregation, rename."""

from __future__ import annotations

from functools import reduce as fold

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def select_rows(df: DataFrame, predicate: Column | str) -> DataFrame:
    return df.where(predicate)


def project(df: DataFrame, cols: list) -> DataFrame:
    return df.select(*cols)


def project_types(df: DataFrame, *types: str) -> DataFrame:
    """Columns of the given types, in order."""
    return df.select(*[c for c, t in df.dtypes if t in types])


def map_columns(df: DataFrame, exprs: dict[str, Column]) -> DataFrame:
    return df.withColumns(exprs)


def map_scalar(df: DataFrame, cols: list[str], op: str, value) -> DataFrame:
    """Arithmetic of columns with one scalar: add, sub, mul, div, mod, pow."""
    fns = {"add": lambda c: c + value, "sub": lambda c: c - value, "mul": lambda c: c * value, "div": lambda c: c / value, "mod": lambda c: c % value, "pow": lambda c: F.pow(c, F.lit(value))}
    return df.withColumns({c: fns[op](F.col(c)) for c in cols})


def sample_rows(df: DataFrame, share: float, label: list[str], by: str | None = None, shares: dict | None = None) -> DataFrame:
    """A repeatable share of the rows, by the hash of their labels; samples of one label nest.

    With ``by`` and ``shares`` every stratum has its own share, ``share`` where none is listed.
    """
    edge = lambda x: f"{round(x * (1 << 32)):08x}" if x < 1 else "g"  # noqa: E731  "g" is above every digit
    limit = F.lit(edge(share))
    for value, part in (shares or {}).items():
        limit = F.when(F.col(by) == value, edge(part)).otherwise(limit)
    return df.where(F.substring(F.md5(F.concat_ws("|", *[F.col(c).cast("string") for c in label])), 1, 8) < limit)


def clip(c: Column, low=None, high=None) -> Column:
    c = c if low is None else F.greatest(c, F.lit(low))
    return c if high is None else F.least(c, F.lit(high))


def mask(c: Column, where: Column, other=None) -> Column:
    """``other`` (null) where the condition holds."""
    return F.when(where, F.lit(other)).otherwise(c)


def row_agg(cols: list[str], how: str) -> Column:
    """Aggregate over the columns of one row; nulls are skipped, a row of nulls gives null (0 for count and sum)."""
    cs = [F.col(c) for c in cols]
    count = fold(lambda a, b: a + b, [c.isNotNull().cast("int") for c in cs])
    total = fold(lambda a, b: a + b, [F.coalesce(c, F.lit(0)) for c in cs])
    if how == "count":
        return count
    if how == "sum":
        return total
    if how == "mean":
        return F.when(count > 0, total / count)
    if how == "min":
        return F.least(*cs)
    if how == "max":
        return F.greatest(*cs)
    if how == "any":
        return fold(lambda a, b: a | b, [F.coalesce(c.cast("boolean"), F.lit(False)) for c in cs])
    if how == "all":
        return fold(lambda a, b: a & b, [F.coalesce(c.cast("boolean"), F.lit(True)) for c in cs])
    if how == "std":
        mean = total / count
        squares = fold(lambda a, b: a + b, [F.coalesce((c - mean) * (c - mean), F.lit(0)) for c in cs])
        return F.when(count > 1, F.sqrt(squares / (count - 1)))
    raise ValueError(how)


def rename(df: DataFrame, names: dict[str, str] | None = None, prefix: str = "", suffix: str = "") -> DataFrame:
    return df.withColumnsRenamed(names) if names else df.toDF(*[f"{prefix}{c}{suffix}" for c in df.columns])
