"""Rows and bytes that a query writes into its shuffles."""

from __future__ import annotations

import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame


@dataclass(frozen=True)
class Volume:
    rows: int
    bytes: int


def shuffle_volume(df: DataFrame) -> Volume:
    """Run the query into a sink that drops its input and add up its stages' shuffle writes."""
    sc, group = df.sparkSession.sparkContext, f"volume-{uuid.uuid4().hex}"
    sc.setJobGroup(group, "shuffle volume")
    try:
        df.write.format("noop").mode("overwrite").save()
    finally:
        sc._jsc.clearJobGroup()
    sc._jsc.sc().listenerBus().waitUntilEmpty(10_000)
    store, tracker = sc._jsc.sc().statusStore(), sc.statusTracker()
    stages = {s for j in tracker.getJobIdsForGroup(group) for s in tracker.getJobInfo(j).stageIds}
    rows = size = 0
    for s in stages:
        try:
            last = store.lastStageAttempt(s)
        except Exception:  # a stage that was skipped has no attempt
            continue
        rows += last.shuffleWriteRecords()
        size += last.shuffleWriteBytes()
    return Volume(rows, size)
