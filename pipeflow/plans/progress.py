"""Progress: one fraction for a whole run, from the time shares of the largest earlier run."""

from __future__ import annotations

import inspect
import threading

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

RUNS = "pipeline_id string, run_id string, size long, phase int, seconds double, steps long"


def identity(depth: int = 1) -> str:
    """Where in the code the pipeline is defined: file, line and function of the caller."""
    f = inspect.stack()[depth]
    return f"{f.filename}:{f.lineno}:{f.function}"


def fraction(shares: list[float], phase: int, done: float, total: float) -> float:
    """Shares of the phases before, and of this phase the part that is done. phase counts from 0."""
    part = min(done / total, 1.0) if total else 1.0
    return min(1.0, sum(shares[:phase]) + shares[phase] * part)


def shares_by_steps(steps: list[int]) -> list[float]:
    """Without history: in proportion to the announced steps."""
    whole = sum(steps)
    return [s / whole for s in steps] if whole else [1 / len(steps)] * len(steps)


def equal_shares(n: int) -> list[float]:
    return [1 / n] * n


class ProgressStore:
    """The execution-time database: a folder of Parquet files, a row a phase and run."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def record(self, pipeline_id: str, run_id: str, size: int, seconds: list[float], steps: list[int]) -> None:
        rows = [(pipeline_id, run_id, size, k, float(s), int(n)) for k, (s, n) in enumerate(zip(seconds, steps, strict=True))]
        self.spark.createDataFrame(rows, RUNS).coalesce(1).write.mode("append").parquet(self.path)

    def runs(self) -> DataFrame:
        p = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        if not p.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(p):
            return self.spark.createDataFrame([], RUNS)
        return self.spark.read.schema(RUNS).parquet(self.path)

    def shares(self, pipeline_id: str) -> list[float] | None:
        rows = largest_run(self.runs().where(F.col("pipeline_id") == pipeline_id)).orderBy("phase").collect()
        whole = sum(r.seconds for r in rows)
        return [r.seconds / whole for r in rows] if whole else None


def largest_run(runs: DataFrame) -> DataFrame:
    """The rows of each pipeline's run of largest size; of equals, the latest."""
    best = runs.groupBy("pipeline_id").agg(F.max(F.struct("size", "run_id")).alias("b")).select("pipeline_id", "b.run_id")
    return runs.join(best, ["pipeline_id", "run_id"], "left_semi")


def part_of(a: Column, whole: Column) -> Column:
    """a / whole; where whole is 0, what floating point gives (NaN for 0 / 0), in place of Spark's error."""
    return F.when(whole == 0, a * F.lit(float("inf"))).otherwise(a / whole)


def shares_df(runs: DataFrame) -> DataFrame:
    """(pipeline_id, phase, share) of every pipeline, from its largest run; NaN where that run took no time."""
    w = Window.partitionBy("pipeline_id")
    return largest_run(runs).withColumn("share", part_of(F.col("seconds"), F.sum("seconds").over(w))).select("pipeline_id", "phase", "share")


def curve_df(log: DataFrame, keys: list[str], order: list[str], seconds: Column, share: Column) -> DataFrame:
    """log with t, the part of the run's time gone after each row (NaN in a run that took none), and p, the bar's fraction there."""
    w = Window.partitionBy(*keys)
    upto = w.orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    return log.withColumn("t", part_of(F.sum(seconds).over(upto), F.sum(seconds).over(w))).withColumn("p", F.sum(share).over(upto))


def pace_error(curve: DataFrame, keys: list[str]) -> DataFrame:
    """The greatest distance of the bar from constant pace, a row a run."""
    return curve.groupBy(*keys).agg(F.max(F.abs(F.col("p") - F.col("t"))).alias("err"))


def tasks_done(spark: SparkSession, group: str) -> tuple[int, int]:
    """(tasks that have ended, tasks) of the stages of a job group that are known so far."""
    tracker = spark.sparkContext.statusTracker()
    done = total = 0
    for job in tracker.getJobIdsForGroup(group):
        info = tracker.getJobInfo(job)
        for stage in info.stageIds if info else ():
            s = tracker.getStageInfo(stage)
            if s:
                done, total = done + s.numCompletedTasks, total + s.numTasks
    return done, total


class Ticker:
    """Moves the bar while a phase runs: every few moments, by the tasks of the phase's job group that have ended.

    The bar never goes back, though later stages add tasks, and stays below the phase's end until the phase has ended.
    """

    def __init__(self, spark: SparkSession, group: str, shares: list[float], phase: int, ticks: list[tuple[int, float]], every: float = 0.05):
        self.args, self.ticks, self.every = (spark, group, shares, phase), ticks, every
        self.stop = threading.Event()
        self.thread = threading.Thread(target=self._run, daemon=True)

    def _run(self) -> None:
        spark, group, shares, phase = self.args
        at = fraction(shares, phase, 0, 1)
        while not self.stop.wait(self.every):
            done, total = tasks_done(spark, group)
            now = fraction(shares, phase, done, total) if total else at
            if done < total and now > at:
                at = now
                self.ticks.append((phase, at))

    def __enter__(self) -> Ticker:
        self.thread.start()
        return self

    def __exit__(self, *failed) -> None:
        self.stop.set()
        self.thread.join()


def phase_seconds(stages: list[tuple[int, float]], phases: int) -> list[float]:
    """Seconds of each phase of a run that was one job: its stages in order, (number, seconds).

    An exchange ends a phase, so the last phases own one stage each, and all stages before them read the sources of the first.
    """
    out = [0.0] * phases
    for k, (_, seconds) in enumerate(sorted(stages)):
        out[max(0, k - (len(stages) - phases))] += seconds
    return out


def from_streaming(query, total: int) -> float:
    """The bar of a stream over a bounded source: rows read so far against those there are."""
    return min(1.0, sum(p["numInputRows"] for p in query.recentProgress) / total) if total else 1.0
