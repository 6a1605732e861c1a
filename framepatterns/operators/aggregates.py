"""Aggregates by how they combine: distributive, algebraic, holistic; and aggregates that a user declares."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

DISTRIBUTIVE, ALGEBRAIC, HOLISTIC = "distributive", "algebraic", "holistic"

KINDS = {
    "count": DISTRIBUTIVE, "size": DISTRIBUTIVE, "sum": DISTRIBUTIVE, "min": DISTRIBUTIVE, "max": DISTRIBUTIVE, "prod": DISTRIBUTIVE, "any": DISTRIBUTIVE, "all": DISTRIBUTIVE, "first": DISTRIBUTIVE, "last": DISTRIBUTIVE,
    "mean": ALGEBRAIC, "var": ALGEBRAIC, "std": ALGEBRAIC, "std_moments": ALGEBRAIC, "skew": ALGEBRAIC, "kurt": ALGEBRAIC, "nunique_approx": ALGEBRAIC, "quantile_approx": ALGEBRAIC,
    "nunique": HOLISTIC, "median": HOLISTIC, "quantile": HOLISTIC, "mode": HOLISTIC, "list": HOLISTIC, "set": HOLISTIC,
}


@dataclass(frozen=True)
class Partial:
    """A declared aggregate: named partial aggregates (each combinable) and the final expression over them."""

    parts: dict[str, Callable[[Column], Column]]
    finish: Callable[..., Column]

    def column(self, c: Column) -> Column:
        return self.finish(*[f(c) for f in self.parts.values()])


#: Standard deviation from the sum of squares, the sum and the count (cancels badly for large means).
STD_MOMENTS = Partial(
    {"sum_x2": lambda c: F.sum(c * c), "sum_x": F.sum, "count_x": F.count},
    lambda s2, s, n: F.when(n > 1, F.sqrt(F.greatest((s2 - s * s / n) / (n - 1), F.lit(0.0)))),
)
#: Geometric mean: a declared aggregate that combines through sums of logarithms.
GEOMETRIC_MEAN = Partial({"logs": lambda c: F.sum(F.ln(c)), "n": F.count}, lambda s, n: F.exp(s / n))


def aggregate(how: str | Partial, c: Column, label: Column | None = None, ddof: int = 1, q: float = 0.5) -> Column:
    """The column expression of a named or declared aggregate; first and last go by ``label``."""
    if isinstance(how, Partial):
        return how.column(c)
    simple = {
        "count": F.count, "sum": F.sum, "min": F.min, "max": F.max, "prod": F.product, "mean": F.avg, "any": F.bool_or, "all": F.bool_and,
        "skew": F.skewness, "kurt": F.kurtosis, "nunique": F.countDistinct, "nunique_approx": F.approx_count_distinct, "median": F.median,
        "mode": lambda x: F.mode(x, True), "list": F.collect_list, "set": F.collect_set, "std_moments": STD_MOMENTS.column,
    }
    if how in simple:
        return simple[how](c)
    if how == "size":
        return F.count(F.lit(1))
    if how == "var":
        return F.var_samp(c) if ddof else F.var_pop(c)
    if how == "std":
        return F.stddev_samp(c) if ddof else F.stddev_pop(c)
    if how == "quantile":
        return F.percentile(c, F.lit(q))
    if how == "quantile_approx":
        return F.percentile_approx(c, q)
    if how in ("first", "last"):
        if label is None:
            raise ValueError(f"{how} needs a label to order by")
        return (F.min_by if how == "first" else F.max_by)(c, label)
    raise ValueError(how)


def classify(hows: list) -> str:
    """The hardest class among the aggregates: it decides whether partial aggregation is possible at all."""
    kinds = [ALGEBRAIC if isinstance(h, Partial) else KINDS[h] for h in hows]
    return HOLISTIC if HOLISTIC in kinds else ALGEBRAIC if ALGEBRAIC in kinds else DISTRIBUTIVE
