"""Transpose, pivot and melt."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from framepatterns.model import whole_input
from framepatterns.patterns import transpose_compute

MAX_COLUMNS = 1000


def transpose(df: DataFrame, index: str, form: str = "cells", block: int = 4096, max_columns: int = MAX_COLUMNS) -> DataFrame:
    """Swap rows and columns.

    cells: (column, label, value).  blocks: (column, block, values), the values of one block of rows in order,
    so a wide result stays distributed.  wide: one row a column and one column a row, only for few rows.
    Mixed column types become strings.
    """
    values = [c for c in df.columns if c != index]
    types = {t for c, t in df.dtypes if c != index}
    cast = "string" if len(types) > 1 else types.pop()
    typed = df.select(index, *[F.col(c).cast(cast).alias(c) for c in values])
    if form == "cells":  # row-local: the one form that a stream can have
        return typed.unpivot([index], values, "column", "value").select("column", F.col(index).alias("label"), "value")
    whole_input(df, "a transpose")
    if form == "blocks":
        return transpose_compute(typed, index, block=block).df
    labels = [r[0] for r in typed.select(index).orderBy(index).limit(max_columns + 1).collect()]
    if len(labels) > max_columns:
        raise ValueError(f"a wide transpose of more than {max_columns} rows is refused; use blocks")
    return typed.unpivot([index], values, "column", "value").groupBy("column").pivot(index, labels).agg(F.first("value"))


def pivot(df: DataFrame, index: list[str], columns: str, values: list, agg) -> DataFrame:
    """Spread the listed values of a column into columns; listing them saves a pass."""
    return df.groupBy(*index).pivot(columns, values).agg(agg)


def melt(df: DataFrame, index: list[str], values: list[str], name: str = "column", value: str = "value") -> DataFrame:
    return df.unpivot(index, values, name, value)
