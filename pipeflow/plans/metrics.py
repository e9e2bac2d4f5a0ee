"""Measured traffic of finished jobs, and how much of a plan is fused into generated code."""

from __future__ import annotations

import io
import re
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager, redirect_stdout

from pyspark.sql import DataFrame, SparkSession

STAGE = "stage int, in_records long, out_records long, shuffle_read long, shuffle_write long, spilled long, seconds double"


@contextmanager
def job_group(spark: SparkSession) -> Iterator[str]:
    """Jobs inside belong to a group of their own; the group's name."""
    group = f"pipeflow-{uuid.uuid4().hex}"
    spark.sparkContext.setJobGroup(group, group)
    try:
        yield group
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


def stage_seconds(spark: SparkSession, group: str) -> list[tuple[int, float]]:
    """(stage, seconds its tasks ran) of the group's stages."""
    return [(r.stage, r.seconds) for r in stage_traffic(spark, group).select("stage", "seconds").collect()]


def run_in_group(spark: SparkSession, job: Callable[[], object]) -> str:
    """Runs job under a job group of its own; the group's name."""
    with job_group(spark) as group:
        job()
    return group


def settled(spark: SparkSession) -> None:
    """Returns when the session's listeners have seen all that has happened so far."""
    spark._jsc.sc().listenerBus().waitUntilEmpty()


def stage_traffic(spark: SparkSession, group: str) -> DataFrame:
    """A row for each stage of the group that ran to its end: records read and written, shuffled and spilled bytes."""
    tracker = spark.sparkContext.statusTracker()
    wanted = {s for j in tracker.getJobIdsForGroup(group) for s in (tracker.getJobInfo(j).stageIds if tracker.getJobInfo(j) else ())}
    store = spark._jsc.sc().statusStore()
    stages = store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), None)
    rows = []
    for i in range(stages.size()):
        s = stages.apply(i)
        if s.stageId() in wanted and s.status().toString() == "COMPLETE":
            rows.append((s.stageId(), s.inputRecords(), s.outputRecords(), s.shuffleReadRecords(), s.shuffleWriteRecords(), s.diskBytesSpilled(), s.executorRunTime() / 1000))
    return spark.createDataFrame(rows, STAGE)


def plan_text(df: DataFrame, mode: str = "formatted") -> str:
    out = io.StringIO()
    with redirect_stdout(out):
        df.explain(mode)
    return out.getvalue()


def codegen_spans(df: DataFrame) -> int:
    """Generated-code stages of the plan, as it is before adaptive execution changes it."""
    conf, key = df.sparkSession.conf, "spark.sql.adaptive.enabled"
    before = conf.get(key)
    conf.set(key, "false")
    try:
        return len(set(re.findall(r"\*\((\d+)\)", plan_text(df.select("*"), "simple"))))
    finally:
        conf.set(key, before)


def exchanges(df: DataFrame) -> int:
    return len(re.findall(r"^\s*[+:\- ]*\s*Exchange\b", plan_text(df, "simple"), re.M))
