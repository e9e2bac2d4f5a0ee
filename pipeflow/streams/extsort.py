"""External merge sort step by step: runs of m items, merges of fan_in runs, passes until one run is left."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pipeflow.grid.shape import div
from pipeflow.plans.cost import external_sort_traffic
from pipeflow.session import materialise, partitions


def form_runs(s: DataFrame, m: int) -> DataFrame:
    """s has pos, the order of arrival -> run_id: m items at a time."""
    return s.withColumn("run_id", div(F.col("pos"), m))


def in_runs(df: DataFrame, key: list[str]) -> DataFrame:
    """Runs to partitions, each sorted: rows of a run are adjacent and in order."""
    return df.repartition(partitions(df.sparkSession), "run_id").sortWithinPartitions("run_id", *key)


def numbered(df: DataFrame, key: list[str]) -> DataFrame:
    """pos_in_run of each row. A run is at most as long as its pass makes it; the last pass is numbered by range instead."""
    w = Window.partitionBy("run_id").orderBy(*key)
    return df.withColumn("pos_in_run", F.row_number().over(w).cast("long") - 1)


def merge_runs(runs: DataFrame, fan_in: int) -> DataFrame:
    return runs.withColumn("run_id", div(F.col("run_id"), fan_in))


def external_sort(s: DataFrame, key: list[str], m: int, fan_in: int, stored: bool = True) -> DataFrame:
    """The passes one after another, each stored as the real thing would. s has pos.

    Passes with many runs deal whole runs to tasks. The last one leaves a single run: it is dealt by ranges of the key, so
    that each task merges its slice of all runs, and comes out in order from partition to partition; unless `stored`, it
    is left to its reader to store.
    """
    n = s.count()
    out = materialise(in_runs(form_runs(s, m), key), "runs")
    passes = external_sort_traffic(n, m, fan_in)[1]
    for k in range(passes):
        merged = merge_runs(out, fan_in)
        if k < passes - 1:
            out = materialise(in_runs(merged, key), "runs")
        else:
            out = merged.repartitionByRange(partitions(s.sparkSession), *key).sortWithinPartitions(*key)
            out = materialise(out, "runs") if stored else out
    return out


def run_stats(runs: DataFrame, key: str) -> DataFrame:
    return runs.groupBy("run_id").agg(F.min(key).alias("low"), F.max(key).alias("high"), F.count("*").alias("items"))
