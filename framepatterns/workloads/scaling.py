"""Strong scaling and the cardinality sweep, as tables.

Parallelism is the number of cores, and of partitions that hold the input: scaling.py starts a session for each.
One machine cannot show the published range, so rows and bytes sent and the balance of the partitions are
reported next to seconds.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from framepatterns.baselines import serial
from framepatterns.measure.balance import balance
from framepatterns.measure.shuffle_volume import shuffle_volume
from framepatterns.measure.timing import timed
from framepatterns.operators import columnagg, grouping, joining, ordering, rows
from framepatterns.plans.cardinality import cardinality, combine_ratio
from framepatterns.plans.choose import choose_group_pattern
from framepatterns.workloads.frames import UNIVERSE, bench_a, bench_b

AGGS = {"total": ("v", "sum"), "mean": ("v", "mean"), "std": ("v", "std")}


def spread(df: DataFrame, partitions: int, copies: int = 1) -> DataFrame:
    """The input in ``partitions`` partitions, in memory; ``copies`` repeats its rows under other keys."""
    from pyspark.sql import functions as F

    big = df.select("k", "v", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))).alias("c")).select((F.col("k") * copies + F.col("c")).alias("k"), "v") if copies > 1 else df
    out = big.repartition(partitions).cache()
    out.count()
    return out


def strong_scaling_table(spark: SparkSession, sf_dir: str, parallelism: list[int], copies: int = 1, reps: int = 3) -> list[dict]:
    """Seconds of the four operators at each parallelism, and of the serial library."""
    out = []
    a, b = bench_a(spark, sf_dir, 0.9), bench_b(spark, sf_dir, 0.9)
    pa, pb = spread(a, 1, copies).toPandas(), spread(b, 1, copies).toPandas()
    base = {
        "scalar": serial.seconds(lambda: serial.scalar_add(pa, 42), reps),
        "scalar aggregation": serial.seconds(lambda: serial.column_sum(pa), reps),
        "group-by": serial.seconds(lambda: serial.group(pa, "k", "v"), reps),
        "join": serial.seconds(lambda: serial.join(pa, pb, "k"), reps),
    }
    for p in parallelism:
        x, y = spread(a, p, copies), spread(b, p, copies)
        runs = {
            "scalar": lambda: rows.map_scalar(x, ["k", "v"], "add", 42),
            "scalar aggregation": lambda: columnagg.column_agg(x, {"k": ("k", "sum"), "v": ("v", "mean")}),
            "group-by": lambda: grouping.groupby(x, ["k"], AGGS, "shuffle", partitions=p).df,
            "join": lambda: joining.join(x, y, ["k"], partitions=p).df,
        }
        even = balance(x).max_over_mean
        for name, make in runs.items():
            run = timed(make, reps)
            out.append({"operator": name, "parallelism": p, "seconds": run.seconds, "speed_up": base[name] / run.seconds if run.seconds else None, "max_over_mean": even, "failure": run.failure})
        x.unpersist()
        y.unpersist()
    return out + [{"operator": n, "parallelism": 0, "seconds": s, "speed_up": 1.0, "max_over_mean": None, "failure": None} for n, s in base.items()]


def sort_table(spark: SparkSession, sf_dir: str, partitions: int, copies: int = 1, reps: int = 3) -> list[dict]:
    """Both sorts and the engine's own on even and on hot keys: seconds, and the longest partition over the mean."""
    from pyspark.sql import functions as F

    x = spread(bench_a(spark, sf_dir, 0.9), partitions, copies)
    out = []
    for keys, df in (("even", x), ("half in one key", x.withColumn("k", F.when(F.col("v") % 2 == 0, 0).otherwise(F.col("k"))))):
        for algorithm in ("range", "sample", "native"):
            make = lambda a=algorithm, d=df: ordering.sort(d, ["k"], algorithm=a, partitions=partitions).df
            out.append({"keys": keys, "algorithm": algorithm, "seconds": timed(make, reps).seconds, "max_over_mean": balance(make()).max_over_mean})
    x.unpersist()
    return out


def cardinality_table(spark: SparkSession, sf_dir: str, partitions: int, copies: int = 1, reps: int = 3) -> list[dict]:
    """Both group-by patterns at every cardinality: seconds, rows and bytes sent, the measured ratio and the choice."""
    out = []
    for c in UNIVERSE:
        x = spread(bench_a(spark, sf_dir, c), partitions, copies)
        for pattern in ("shuffle", "combine"):
            make = lambda p=pattern: grouping.groupby(x, ["k"], AGGS, p, partitions=partitions).df
            v = shuffle_volume(make())
            out.append({"C": c, "pattern": pattern, "seconds": timed(make, reps).seconds, "rows": v.rows, "bytes": v.bytes, "measured_C": cardinality(x, ["k"]), "ratio": combine_ratio(x, ["k"]), "choice": choose_group_pattern(x, ["k"]).pattern})
        x.unpersist()
    return out


def markdown(rows_: list[dict]) -> str:
    heads = list(rows_[0])
    cell = lambda v: f"{v:.4g}" if isinstance(v, float) else "" if v is None else str(v)
    return "\n".join(["| " + " | ".join(heads) + " |", "|" + "---|" * len(heads), *["| " + " | ".join(cell(r[h]) for h in heads) + " |" for r in rows_]])
