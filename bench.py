"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

HEADLINE = (
    "w1_scalar", "w1_scalar_barrier", "w2_scalar_agg", "w3_groupby", "w3_groupby_stock", "w4_join", "w4_join_stock", "w4_join_fk", "w5_join_broadcast_only",
    "w6_hash_C09", "w6_mapred_C09", "w6_hash_Clow", "w6_mapred_Clow", "w7_join_shuffle", "w7_join_swap", "w10_pipeline",
    "groupby_shuffle_highC", "groupby_combine_lowC", "sort_range", "sort_sample", "sort_native", "rolling_count_global", "b7_stock_rolling", "expanding_global", "transpose_cells", "join_asof", "join_skew_salted", "unique_shuffle",
)


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", str(os.cpu_count()))
    sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
    os.environ["PYTHONPATH"] = os.pathsep.join([sys.path[0], os.environ.get("PYTHONPATH", "")])
    from framepatterns import catalog, session
    from framepatterns.baselines import serial
    from framepatterns.measure.shuffle_volume import shuffle_volume
    from framepatterns.operators import grouping
    from framepatterns.workloads.frames import bench_a, bench_b

    spark = session.start(f"local[{cpus}]", "bench", **{"spark.sql.shuffle.partitions": cpus, "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false", "spark.driver.memory": "8g"})
    spark.sparkContext.setLogLevel("ERROR")
    queries, took = catalog.queries(), {}
    for name in HEADLINE:
        best = None
        for _ in range(3):
            began = time.perf_counter()
            queries[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
            s = time.perf_counter() - began
            best = s if best is None else min(best, s)
        took[name] = round(best, 3)
    volumes = {}
    for c in (0.9, 1e-5):
        spread = bench_a(spark, sf_dir, c).repartition(int(cpus))  # one row group a file: spread the rows before measuring
        spread.cache().count()
        for pattern in ("shuffle", "combine"):
            v = shuffle_volume(grouping.groupby(spread, ["k"], {"total": ("v", "sum"), "std": ("v", "std")}, pattern, partitions=int(cpus)).df)
            volumes[f"{pattern}_C{c:g}"] = {"rows": v.rows, "bytes": v.bytes}
        spread.unpersist()
    pa, pb = bench_a(spark, sf_dir, 0.9).toPandas(), bench_b(spark, sf_dir, 0.9).toPandas()
    base = {"scalar": serial.seconds(lambda: serial.scalar_add(pa, 42)), "scalar_agg": serial.seconds(lambda: serial.column_sum(pa)), "groupby": serial.seconds(lambda: serial.group(pa, "k", "v")), "join": serial.seconds(lambda: serial.join(pa, pb, "k"))}
    spark.stop()
    print(json.dumps({"metric": "headline queries, total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(sf_dir.rstrip("/")), "shuffle_written": volumes, "serial_sec": {k: round(v, 4) for k, v in base.items()}}))


if __name__ == "__main__":
    main()
