"""Wall-clock time, speed-up, efficiency and completion."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame


@dataclass(frozen=True)
class Run:
    seconds: float | None
    failure: str | None = None

    @property
    def completed(self) -> bool:
        return self.failure is None


def timed(make: Callable[[], DataFrame], reps: int = 3) -> Run:
    """Best of ``reps`` full executions into a sink that drops its input; a failure is recorded, not raised."""
    best = None
    for _ in range(reps):
        began = time.perf_counter()
        try:
            make().write.format("noop").mode("overwrite").save()
        except Exception as e:
            return Run(None, f"{type(e).__name__}: {str(e).splitlines()[0][:200]}")
        took = time.perf_counter() - began
        best = took if best is None else min(best, took)
    return Run(best)


def speed_up(serial: Run, run: Run) -> float | None:
    return serial.seconds / run.seconds if serial.seconds and run.seconds else None


def efficiency(serial: Run, run: Run, parallelism: int) -> float | None:
    s = speed_up(serial, run)
    return s / parallelism if s else None


def strong_scaling(make: Callable[[int], DataFrame], parallelism: list[int], reps: int = 2) -> dict[int, Run]:
    """The same input at growing parallelism; ``make(p)`` builds the query over p partitions."""
    return {p: timed(lambda p=p: make(p), reps) for p in parallelism}
