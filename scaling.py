"""Print the strong-scaling, cardinality and sort tables: python scaling.py [directory of tables] [copies of the rows].

Every parallelism runs in a program of its own with that many cores and as many partitions.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys


def measure(cores: int, sf_dir: str, copies: int, what: str) -> list[dict]:
    from framepatterns import session
    from framepatterns.workloads import scaling

    spark = session.start(f"local[{cores}]", "scaling", **{"spark.sql.shuffle.partitions": str(cores), "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false", "spark.driver.memory": "8g", "spark.sql.autoBroadcastJoinThreshold": "-1"})
    spark.sparkContext.setLogLevel("ERROR")
    try:
        if what == "scaling":
            return scaling.strong_scaling_table(spark, sf_dir, [cores], copies)
        return (scaling.sort_table if what == "sorts" else scaling.cardinality_table)(spark, sf_dir, cores, copies)
    finally:
        spark.stop()


def main() -> None:
    sf_dir, copies = (sys.argv[1:] + ["/root/testdata/sf0.1"])[0], int((sys.argv[2:] + ["1"])[0])
    os.environ["PYTHONPATH"] = os.path.dirname(os.path.abspath(__file__))
    if len(sys.argv) > 3:
        print("rows:" + json.dumps(measure(int(sys.argv[4]), sf_dir, copies, sys.argv[3])))
        return
    from framepatterns.workloads.scaling import markdown

    cpus = os.cpu_count() or 4

    def run(what: str, cores: int) -> list[dict]:
        out = subprocess.run([sys.executable, os.path.abspath(__file__), sf_dir, str(copies), what, str(cores)], capture_output=True, text=True, check=True).stdout
        return json.loads(next(x for x in out.splitlines() if x.startswith("rows:"))[5:])

    rows: list[dict] = []
    for p in [p for p in (1, 2, 4, 8, 16, 32) if p <= cpus]:
        rows += [r for r in run("scaling", p) if r["parallelism"] or not any(x["parallelism"] == 0 and x["operator"] == r["operator"] for x in rows)]
    print(markdown(sorted(rows, key=lambda r: (r["operator"], r["parallelism"]))), end="\n\n")
    print(markdown(run("cardinality", cpus)), end="\n\n")
    print(markdown(run("sorts", cpus)))


if __name__ == "__main__":
    main()
