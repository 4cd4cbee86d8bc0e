"""Wall time, passes and shuffled bytes of a job, for reports beside its bits."""

from __future__ import annotations

import time
from collections.abc import Callable
from typing import Any

from pyspark.sql import SparkSession


def profile(spark: SparkSession, job: Callable[[], Any]) -> tuple[Any, dict[str, float]]:
    """The job's result, and its seconds, Spark jobs and stages; jobs are those of a group of their own."""
    context = spark.sparkContext
    group = f"profile-{time.time_ns()}"
    context.setJobGroup(group, "profiled")
    began = time.time()
    try:
        result = job()
    finally:
        seconds = time.time() - began
        jobs = list(context.statusTracker().getJobIdsForGroup(group))
        context._jsc.clearJobGroup()
    stages = sum(len(info.stageIds) for j in jobs if (info := context.statusTracker().getJobInfo(j)) is not None)
    return result, {"seconds": seconds, "jobs": float(len(jobs)), "stages": float(stages)}
