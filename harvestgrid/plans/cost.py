"""What a plan cost when it ran: wall time, stages, tasks, bytes and records shuffled, spill."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame


def measure(df: DataFrame) -> dict[str, float]:
    """Run ``df`` into nothing and report the work of its stages."""
    context = df.sparkSession.sparkContext
    store = context._jsc.sc().statusStore()
    group = f"cost-{time.time_ns()}"
    context.setJobGroup(group, "cost")
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    wall = time.perf_counter() - began
    context._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    out = {"wall_s": wall, "stages": 0, "tasks": 0, "shuffle_bytes": 0, "shuffle_records": 0, "input_records": 0, "spill_bytes": 0}
    tracker = context.statusTracker()
    for job in tracker.getJobIdsForGroup(group):
        info = tracker.getJobInfo(job)
        for stage in info.stageIds if info else ():
            try:
                s = store.lastStageAttempt(stage)
            except Exception:  # a stage that was skipped has no record
                continue
            out["stages"] += 1
            out["tasks"] += s.numCompleteTasks()
            out["shuffle_bytes"] += s.shuffleWriteBytes()
            out["shuffle_records"] += s.shuffleWriteRecords()
            out["input_records"] += s.inputRecords()
            out["spill_bytes"] += s.diskBytesSpilled()
    context.setLocalProperty("spark.jobGroup.id", None)
    return out
