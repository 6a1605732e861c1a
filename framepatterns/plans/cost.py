"""Predicted communication cost, in rows sent per partition."""

from __future__ import annotations

import math


def shuffle_compute_cost(rows: int, partitions: int) -> float:
    n = rows / partitions
    return n + n * math.log2(max(partitions, 2))


def combine_cost(rows: int, partitions: int, ratio: float) -> float:
    n = rows / partitions
    return n + ratio * n * math.log2(max(partitions, 2))


def broadcast_cost(small_rows: int, partitions: int) -> float:
    return float(partitions * small_rows)


def cheaper_group_pattern(rows: int, partitions: int, ratio: float, local_cost: float = 1.0) -> str:
    """The combine form pays an extra local pass over n rows to send ratio * n of them."""
    combine = combine_cost(rows, partitions, ratio) + local_cost * rows / partitions
    return "combine" if combine < shuffle_compute_cost(rows, partitions) else "shuffle"
