"""Quadratic definitions, for small inputs only."""

from __future__ import annotations


def rolling(values: list, k: int, fn) -> list:
    return [fn(values[i - k + 1 : i + 1]) if i + 1 >= k else None for i in range(len(values))]


def nested_loop(left: list, right: list, test) -> list:
    return [(a, b) for a in left for b in right if test(a, b)]


def rank_dense(values: list) -> list[int]:
    order = {v: i + 1 for i, v in enumerate(sorted(set(values)))}
    return [order[v] for v in values]
