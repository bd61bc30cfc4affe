"""What a query costs on Spark: seconds, jobs, stages and tasks."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def profile(spark: SparkSession, make: Callable[[], DataFrame]) -> dict[str, float]:
    """Run what ``make`` gives to its end, without a result; counts everything that it starts on the way."""
    group, context = f"profile-{uuid.uuid4().hex[:8]}", spark.sparkContext
    context.setJobGroup(group, "profile")
    began = time.time()
    make().write.format("noop").mode("overwrite").save()
    seconds = time.time() - began
    status = context.statusTracker()
    jobs = [j for i in status.getJobIdsForGroup(group) if (j := status.getJobInfo(i))]
    stages = [x for j in jobs for i in j.stageIds if (x := status.getStageInfo(i))]
    return {"seconds": round(seconds, 3), "jobs": len(jobs), "stages": len(stages), "tasks": sum(x.numTasks for x in stages)}
