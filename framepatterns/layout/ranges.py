"""Ordered partitioning: pivots and the partition of a key between them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def key_struct(keys: list[Column]) -> Column:
    """A comparable key: structs compare field by field, nulls first."""
    return F.struct(*[k.alias(f"k{i}") for i, k in enumerate(keys)])


def range_pid(key: Column, pivots: list, literal, strict: bool = False) -> Column:
    """How many pivots are at or below the key (``strict``: below it).

    ``literal`` makes a column from a pivot.  A few pivots are a chain of comparisons; more are a constant
    array searched in halves, so the expression stays in the JVM and costs log P.
    """
    if not pivots:
        return F.lit(0)
    passed = (lambda p: key > p) if strict else (lambda p: key >= p)
    if len(pivots) <= 16:
        return sum((passed(literal(p)).cast("int") for p in pivots), F.lit(0))
    table = F.array(*[literal(p) for p in pivots])
    steps = len(pivots).bit_length()

    def narrow(acc: Column, _: Column) -> Column:
        mid = F.floor((acc["lo"] + acc["hi"]) / 2).cast("int")
        open_ = acc["lo"] < acc["hi"]
        right = open_ & passed(F.element_at(table, F.least(mid, F.lit(len(pivots) - 1)) + 1))
        return F.struct(F.when(right, mid + 1).otherwise(acc["lo"]).alias("lo"), F.when(open_ & ~right, mid).otherwise(acc["hi"]).alias("hi"))

    start = F.struct(F.lit(0).alias("lo"), F.lit(len(pivots)).alias("hi"))
    return F.aggregate(F.sequence(F.lit(1), F.lit(steps)), start, narrow)["lo"]


def spread_pid(below: Column, upto: Column, salt: Column) -> Column:
    """A partition for a key that equals pivots: any from ``below`` (pivots under the key) to ``upto`` (at or under it).

    Equal keys may lie in all of these without breaking the order, so a hot key fills them evenly.
    """
    return (below + F.pmod(salt, (upto - below + 1).cast("long"))).cast("int")


def _number(key: str) -> Column:
    """The key as a finite double; null for null, NaN and the infinities."""
    k = F.col(key).cast("double")
    return F.when(F.isnan(k) | (F.abs(k) == float("inf")), None).otherwise(k)


#: Times that a histogram looks closer at bins which hold too many rows.
ROUNDS = 12


def histogram_pivots(df: DataFrame, key: str, partitions: int, bins: int = 1024, slack: float = 0.25) -> list[float]:
    """Pivots for one numeric key: global range, equal-width histogram, cuts of equal mass.

    A bin in which a cut falls and that holds more than ``slack`` of a partition is cut into bins again, until
    it is small or one value.  So an outlier that flattens the first histogram costs some more passes, and a
    value that fills several partitions is a pivot several times.  The driver holds at most ``bins`` counts for
    each cut.
    """
    if partitions < 2:
        return []
    k = _number(key)
    low, high, total = df.agg(F.min(k), F.max(k), F.count(k)).first()
    if not total:
        return []
    cells = [(low, high, total)]  # smallest and largest key and rows, in order
    most = max(slack * total / partitions, 1.0)
    cuts = [total * i / partitions for i in range(1, partitions)]

    def cut_cells() -> list[int]:
        out, run, at = [], 0, 0
        for c in cuts:
            while at < len(cells) - 1 and run + cells[at][2] <= c:
                run += cells[at][2]
                at += 1
            out.append(at)
        return out

    for _ in range(ROUNDS):
        wide = sorted({i for i in cut_cells() if cells[i][2] > most and cells[i][0] < cells[i][1]})
        if not wide:
            break
        inside = range_pid(k, [cells[i][0] for i in wide], F.lit) - 1
        ends = F.array(*[F.struct(F.lit(cells[i][0]).alias("lo"), F.lit(cells[i][1]).alias("hi")) for i in wide])
        own = df.select(k.alias("k"), inside.alias("c")).where("c >= 0").withColumn("e", F.element_at(ends, F.col("c") + 1)).where("k <= e.hi")
        share = (F.col("k") / 2 - F.col("e.lo") / 2) / (F.col("e.hi") / 2 - F.col("e.lo") / 2)  # halves: the width may overflow
        found = own.groupBy("c", F.least(F.floor(share * bins), F.lit(bins - 1)).alias("b")).agg(F.min("k"), F.max("k"), F.count("*")).collect()
        closer: dict[int, list] = {}
        for c, _, lo, hi, n in found:
            closer.setdefault(wide[c], []).append((lo, hi, n))
        cells = [x for i, cell in enumerate(cells) for x in (sorted(closer[i]) if i in closer else [cell])]
    return [cells[i][0] for i in cut_cells()]


def quantile_pivots(df: DataFrame, key: str, partitions: int, accuracy: int = 10_000) -> list[float]:
    """Pivots by a mergeable quantile sketch, in one pass; a value that fills several partitions comes several times."""
    cuts = [i / partitions for i in range(1, partitions)]
    if not cuts:
        return []
    return sorted(df.agg(F.percentile_approx(_number(key), cuts, accuracy)).first()[0] or [])
