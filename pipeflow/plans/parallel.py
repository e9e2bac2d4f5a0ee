"""Parallel copies of a component. By default the partitions are the copies; the explicit deal is for skewed inputs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pipeflow.grid.shape import div

BATCH = 2048


def worker_of(pos: Column, batch: int = BATCH, workers: int = 4) -> Column:
    """Round-robin by batches of items as they arrive."""
    return F.pmod(div(pos, batch), F.lit(workers).cast("long"))


def deal(df: DataFrame, pos: str, workers: int, batch: int = BATCH) -> DataFrame:
    """df with each batch at its worker's partition. Order is kept inside a batch only; a later sort restores it."""
    return df.repartitionById(workers, worker_of(F.col(pos), batch, workers).cast("int"))
