"""What a step costs Spark: seconds, jobs, stages and tasks, counted by a job group of its own."""

from __future__ import annotations

import time
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import SparkSession


@contextmanager
def counted(spark: SparkSession, label: str) -> Iterator[dict]:
    """A dict that holds seconds, jobs, stages and tasks of what ran inside, once it is left."""
    context, group, cost = spark.sparkContext, f"{label}-{uuid.uuid4().hex}", {}
    context.setJobGroup(group, label)
    began = time.time()
    try:
        yield cost
    finally:
        tracker = context.statusTracker()
        infos = [tracker.getJobInfo(j) for j in tracker.getJobIdsForGroup(group)]
        ids = {s for i in infos if i for s in i.stageIds}
        stages = [tracker.getStageInfo(s) for s in ids]
        cost |= {"seconds": time.time() - began, "jobs": len(infos), "stages": len(ids), "tasks": sum(s.numTasks for s in stages if s)}
        context.setLocalProperty("spark.jobGroup.id", None)
        context.setLocalProperty("spark.job.description", None)
