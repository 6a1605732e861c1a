"""How evenly rows lie over partitions."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from framepatterns.layout.rebalance import partition_lengths


@dataclass(frozen=True)
class Balance:
    lengths: tuple[int, ...]
    max_over_mean: float
    variation: float


def balance(df: DataFrame) -> Balance:
    n = partition_lengths(df) or [0]
    mean = sum(n) / len(n)
    var = sum((x - mean) ** 2 for x in n) / len(n)
    return Balance(tuple(n), max(n) / mean if mean else 1.0, var**0.5 / mean if mean else 0.0)


def estimator_error(estimate: float, exact: float) -> float:
    return abs(estimate - exact) / exact if exact else abs(estimate)
