"""Measured costs of a plan: rows, tasks, core seconds, rows read and bytes shuffled, from the scheduler's own records."""

from __future__ import annotations

import uuid
from dataclasses import dataclass

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

SCHEMA = "name string, rows long, stages int, tasks long, core_seconds double, cpu_seconds double, rows_read long, shuffle_written long, shuffle_read long, spilled long"


@dataclass
class Measured:
    """What one run of a plan took."""

    name: str
    rows: int
    stages: int = 0
    tasks: int = 0
    core_seconds: float = 0.0
    cpu_seconds: float = 0.0
    rows_read: int = 0
    shuffle_written: int = 0
    shuffle_read: int = 0
    spilled: int = 0

    def row(self) -> tuple:
        return tuple(vars(self).values())


def measure(name: str, build) -> Measured:
    """Builds the plan that ``build()`` returns, runs it into no sink, and adds up all stages that either of them ran.

    Rows read stand for the scan: a local file system's byte counters miss what Parquet reads in threads of its own.
    Stages that are skipped because their shuffle files are there already cost nothing and are not counted.
    """
    from pyspark.sql import SparkSession

    sc = SparkSession.active().sparkContext
    group, before = f"measure-{uuid.uuid4().hex}", sc.getLocalProperty("spark.jobGroup.id")
    told = sc.getLocalProperty("spark.job.description")
    sc.setJobGroup(group, name)
    try:
        seen = Observation()
        build().observe(seen, F.count(F.lit(1)).alias("rows")).write.format("noop").mode("overwrite").save()
        found = Measured(name, int(seen.get["rows"]))
    finally:
        sc.setLocalProperty("spark.jobGroup.id", before)
        sc.setLocalProperty("spark.job.description", told)
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    tracker, records = sc.statusTracker(), sc._jsc.sc().statusStore()
    jobs = [tracker.getJobInfo(j) for j in tracker.getJobIdsForGroup(group)]
    for stage in sorted({s for job in jobs if job for s in job.stageIds}):
        try:
            x = records.lastStageAttempt(stage)
        except Py4JJavaError:  # dropped from the records, or never run
            continue
        if x.status().toString() != "COMPLETE":
            continue
        found.stages += 1
        found.tasks += x.numCompleteTasks()
        found.core_seconds += x.executorRunTime() / 1e3
        found.cpu_seconds += x.executorCpuTime() / 1e9
        found.rows_read += x.inputRecords()
        found.shuffle_written += x.shuffleWriteBytes()
        found.shuffle_read += x.shuffleReadBytes()
        found.spilled += x.diskBytesSpilled()
    return found


def measured(spark, plans: dict) -> DataFrame:
    """A row for each named plan, run one after another; the values are functions that build them."""
    return spark.createDataFrame([measure(name, build).row() for name, build in plans.items()], SCHEMA)
