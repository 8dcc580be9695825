"""Cost and accuracy measures: elapsed time, what jobs shuffled, shuffles of a plan, sketch error."""

from __future__ import annotations

import re
import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def timed(action: Callable[[], object]) -> tuple[float, object]:
    start = time.perf_counter()
    out = action()
    return time.perf_counter() - start, out


@dataclass
class Measured:
    """What an action took: elapsed seconds of its jobs as Spark has them, and of the wall clock; bytes and records that its stages shuffled."""

    seconds: float
    wall: float
    shuffle_bytes: int
    shuffle_records: int
    result: object


def measured(spark: SparkSession, action: Callable[[], object]) -> Measured:
    sc, group = spark.sparkContext, uuid.uuid4().hex
    sc.setJobGroup(group, "measured")
    try:
        wall, out = timed(action)
    finally:
        sc.setLocalProperty("spark.jobGroup.id", None)
        sc.setLocalProperty("spark.job.description", None)
    core = sc._jsc.sc()
    core.listenerBus().waitUntilEmpty()
    store, tracker = core.statusStore(), sc.statusTracker()
    spans, stages = [], set()
    for job in tracker.getJobIdsForGroup(group):
        data = store.job(job)
        if data.submissionTime().isDefined() and data.completionTime().isDefined():
            spans.append((data.submissionTime().get().getTime(), data.completionTime().get().getTime()))
        stages.update(tracker.getJobInfo(job).stageIds)
    moved = [0, 0]
    for stage in stages:
        try:
            data = store.lastStageAttempt(stage)
        except Exception:  # a stage that was skipped, as its output was there, has no attempt
            continue
        moved[0] += data.shuffleWriteBytes()
        moved[1] += data.shuffleWriteRecords()
    busy, end = 0, 0
    for lo, hi in sorted(spans):  # jobs that overlap count once
        busy += max(0, hi - max(lo, end))
        end = max(end, hi)
    return Measured(busy / 1000, wall, moved[0], moved[1], out)


def plan_of(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def shuffles(df: DataFrame) -> int:
    """Exchanges in the physical plan that move rows between tasks."""
    return len(re.findall(r"^[^\w]*Exchange (?:hash|range|Single|RoundRobin)", plan_of(df), re.M))


def python_nodes(df: DataFrame) -> int:
    return len(re.findall(r"(Python|Pandas|Arrow)\w*(?:Exec)? ", plan_of(df)))


def sketch_error(pairs: DataFrame, size: int) -> DataFrame:
    """Mean and largest error of estimated Jaccard indices (j_est, j_exact), and the share within four deviations."""
    off = F.abs(F.col("j_est") - F.col("j_exact"))
    four = 4 * F.sqrt(F.col("j_exact") * (1 - F.col("j_exact")) / size)
    return pairs.agg(F.avg(off).alias("mean_error"), F.max(off).alias("max_error"), F.avg((off <= four + 1e-9).cast("double")).alias("within"))
