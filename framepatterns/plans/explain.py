"""What pattern ran, where rows are now, and which exchanges the plan has."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def physical_plan(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def exchanges(df: DataFrame) -> list[str]:
    """The exchanges of the planned query, in plan order."""
    return re.findall(r"((?:Broadcast)?Exchange [A-Za-z]+(?:\([^)]*\))?)", physical_plan(df))


def single_partition(df: DataFrame) -> bool:
    """Whether some step brings all rows to one partition."""
    return any("SinglePartition" in e for e in exchanges(df))


def python_nodes(df: DataFrame) -> list[str]:
    return sorted(set(re.findall(r"\b(MapInArrow|MapInPandas|ArrowEvalPython|BatchEvalPython|FlatMapGroupsIn\w+|AggregateInPandas)\b", physical_plan(df))))


def explain_frame(frame) -> str:
    lines = [*frame.why, f"layout: {frame.layout}", f"labels: {', '.join(frame.labels) or 'global position'}"]
    return "\n".join(lines + [f"exchange: {e}" for e in exchanges(frame.df)])
