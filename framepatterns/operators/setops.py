"""Set operators on whole rows: shuffle-compute by the hash of all columns."""

from __future__ import annotations

from pyspark.sql import DataFrame


def union_rows(a: DataFrame, b: DataFrame, distinct: bool = True, by: str = "name") -> DataFrame:
    """Bag union moves nothing; set union removes repeated rows."""
    both = a.unionByName(b, allowMissingColumns=True) if by == "name" else a.union(b)
    return both.distinct() if distinct else both


def difference(a: DataFrame, b: DataFrame, multiset: bool = False) -> DataFrame:
    return a.exceptAll(b) if multiset else a.subtract(b)


def intersection(a: DataFrame, b: DataFrame, multiset: bool = False) -> DataFrame:
    return a.intersectAll(b) if multiset else a.intersect(b)


def symmetric_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.subtract(b).union(b.subtract(a))
