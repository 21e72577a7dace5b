"""What a piece of work costs Spark: jobs, stages, tasks, seconds, cached bytes."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from typing import Any

from pyspark.sql import SparkSession


def measure(spark: SparkSession, work: Callable[[], Any]) -> tuple[Any, dict]:
    """(result, costs) of ``work``; cached bytes are those held when it ends."""
    sc, group = spark.sparkContext, uuid.uuid4().hex
    sc.setJobGroup(group, "measured")
    began = time.perf_counter()
    try:
        result = work()
    finally:
        sc.setLocalProperty("spark.jobGroup.id", None)
    seconds = time.perf_counter() - began
    tracker = sc.statusTracker()
    jobs = tracker.getJobIdsForGroup(group)
    stages = {s for j in jobs if (info := tracker.getJobInfo(j)) for s in info.stageIds}
    tasks = sum(info.numTasks for s in stages if (info := tracker.getStageInfo(s)))
    cached = sum(r.memSize() + r.diskSize() for r in sc._jsc.sc().getRDDStorageInfo())
    return result, {"jobs": len(jobs), "stages": len(stages), "tasks": tasks, "seconds": seconds, "cached_bytes": int(cached)}
