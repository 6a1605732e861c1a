"""Pattern choices, with the reason for each."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from framepatterns.collectives import estimated_bytes
from framepatterns.plans.cardinality import combine_ratio

#: Combine ratio above which combining first no longer pays; calibrated by the cardinality sweep of bench.py.
COMBINE_LIMIT = 0.5


@dataclass(frozen=True)
class PatternChoice:
    pattern: str
    reason: str
    side: str = "right"


def choose_group_pattern(df: DataFrame, keys: list[str], kind: str = "algebraic", ratio: float | None = None) -> PatternChoice:
    """Combine first unless the aggregate cannot be combined or a combine would keep most rows."""
    if kind == "holistic":
        return PatternChoice("shuffle", "a holistic aggregate has no partial state of constant size")
    ratio = combine_ratio(df, keys) if ratio is None else ratio
    if ratio > COMBINE_LIMIT:
        return PatternChoice("shuffle", f"a local combine would keep {ratio:.0%} of the rows")
    return PatternChoice("combine", f"a local combine keeps {ratio:.2%} of the rows")


_SIDES = {"inner": ("right", "left"), "cross": ("right", "left"), "left": ("right",), "leftsemi": ("right",), "semi": ("right",), "leftanti": ("right",), "anti": ("right",), "right": ("left",)}


def broadcast_sides(how: str) -> tuple[str, ...]:
    """Which sides may be replicated: never one whose unmatched rows are kept."""
    return _SIDES.get(how.lower().replace("_", "").replace("outer", "") or "full", ())


def broadcast_side(how: str) -> str | None:
    """The side that is replicated first where both may be."""
    return next(iter(broadcast_sides(how)), None)


def broadcast_limit(spark) -> int:
    """The session's limit in bytes for a replicated side; negative where replication is off."""
    text = str(spark.conf.get("spark.sql.autoBroadcastJoinThreshold")).strip().lower()
    unit = {"k": 10, "m": 20, "g": 30, "t": 40}
    digits = text.removesuffix("b")
    shift = unit.get(digits[-1:], 0)
    return int(digits[:-1] if shift else digits) << shift if text.lstrip("-")[:1].isdigit() and not text.startswith("-") else -1


def choose_join_pattern(left: DataFrame, right: DataFrame, how: str, partitions: int | None = None) -> PatternChoice:
    """Broadcast where the join type allows it, the small side is under the session's limit, and P copies cost less than two shuffles."""
    spark = left.sparkSession
    limit = broadcast_limit(spark)
    p = partitions or spark.sparkContext.defaultParallelism
    size = {"left": estimated_bytes(left), "right": estimated_bytes(right)}
    sides = broadcast_sides(how)
    if not sides:
        return PatternChoice("shuffle", f"a {how} join keeps unmatched rows of both sides")
    side = min(sides, key=lambda s: (size[s], s == "left"))
    if size[side] > limit:
        return PatternChoice("shuffle", f"{side} side of {size[side]} bytes is over the limit of {limit}", side)
    if p * size[side] >= sum(size.values()):
        return PatternChoice("shuffle", f"{p} copies of {size[side]} bytes cost more than moving {sum(size.values())} bytes", side)
    return PatternChoice("broadcast", f"{side} side has {size[side]} bytes", side)


def choose_sort(by: list[str], types: dict[str, str]) -> PatternChoice:
    numeric = len(by) == 1 and types[by[0]] in ("tinyint", "smallint", "int", "bigint", "float", "double")
    return PatternChoice("range", "one numeric key") if numeric else PatternChoice("sample", "several keys or no number")
