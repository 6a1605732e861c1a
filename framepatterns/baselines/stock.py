"""The engine as it comes: no control of layout, the planner's own choices."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W


def group(df: DataFrame, keys: list[str], *aggs: Column) -> DataFrame:
    return df.groupBy(*keys).agg(*aggs)


def join(left: DataFrame, right: DataFrame, on: list[str], how: str = "inner") -> DataFrame:
    return left.join(right, on, how)


def sort(df: DataFrame, *by) -> DataFrame:
    return df.orderBy(*by)


def rolling_single(df: DataFrame, order: list[str], k: int, agg: Column) -> DataFrame:
    """A window without a key: all rows meet in one partition."""
    return df.withColumn("rolled", agg.over(W.Window.orderBy(*order).rowsBetween(-(k - 1), 0)))


def position_single(df: DataFrame, order: list[str]) -> DataFrame:
    return df.withColumn("position", F.row_number().over(W.Window.orderBy(*order)) - 1)
