"""What an action costs: jobs, stages, tasks, rows and bytes read and shuffled, and seconds, from the session's own records."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession

SCHEMA = "name string, jobs int, stages int, tasks long, rows_read long, bytes_read long, rows_shuffled long, bytes_shuffled long, bytes_spilled long, task_seconds double, seconds double"


def measured(spark: SparkSession, name: str, make: Callable[[], DataFrame]) -> tuple:
    """Make a frame, read all its rows without keeping them, and tell what that took, as a row of SCHEMA.

    Jobs are told apart by a group of their own, so other threads' jobs do not count; skipped stages cost nothing and are not counted.
    """
    sc, group = spark.sparkContext, f"cost-{uuid.uuid4().hex}"
    sc.setJobGroup(group, name)
    began = time.time()
    try:
        make().write.format("noop").mode("overwrite").save()
    finally:
        sc.setLocalProperty("spark.jobGroup.id", None)
        sc.setLocalProperty("spark.job.description", None)
    seconds = time.time() - began
    inner = sc._jsc.sc()
    inner.listenerBus().waitUntilEmpty()
    jobs = list(sc.statusTracker().getJobIdsForGroup(group))
    ids = {i for j in jobs if (info := sc.statusTracker().getJobInfo(j)) for i in info.stageIds}
    total = [0] * 7
    stages = 0
    for i in ids:
        try:
            told = inner.statusStore().lastStageAttempt(i)
        except Py4JJavaError:  # a stage that was skipped leaves no record
            continue
        if str(told.status()) == "SKIPPED":
            continue
        stages += 1
        values = (told.numCompleteTasks(), told.inputRecords(), told.inputBytes(), told.shuffleWriteRecords(), told.shuffleWriteBytes(), told.memoryBytesSpilled() + told.diskBytesSpilled(), told.executorRunTime())
        total = [a + b for a, b in zip(total, values)]
    return (name, len(jobs), stages, *total[:6], total[6] / 1000, seconds)
