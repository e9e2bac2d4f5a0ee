"""Streams: frames with an order, their global positions, and the blocking kinds sort, delay and reverse.

The active variant of a blocking kind hands its rows on; the passive one is read by its consumer, beside another
stream. Both are the same relation; the passive one is a join's sorted side.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pipeflow.session import materialise, partitions


@dataclass(frozen=True)
class OrderedStream:
    """A frame and the columns that order it totally."""

    df: DataFrame
    order: tuple[str, ...]

    def sort(self, *key: str) -> OrderedStream:
        """The production sorter: range exchange and local sort."""
        out = self.df.repartitionByRange(partitions(self.df.sparkSession), *key).sortWithinPartitions(*key)
        return OrderedStream(out, key)

    def delay(self) -> OrderedStream:
        """Stored, and given again in the order it came in."""
        return OrderedStream(materialise(self.df), self.order)

    def reverse(self, n: int) -> OrderedStream:
        """A stream over pos 0 .. n - 1, the other way round: positions are renamed, nothing moves until a sink wants order."""
        return OrderedStream(self.df.withColumn("pos", F.lit(n - 1) - F.col("pos")), ("pos",))

    def positions(self) -> DataFrame:
        return with_positions(self.df, *self.order)


def with_positions(df: DataFrame, *order: str) -> DataFrame:
    """df with pos, its place in the order. Two passes over a stored range sort; the driver sees one count a partition."""
    return numbered(df.repartitionByRange(partitions(df.sparkSession), *order).sortWithinPartitions(*order))


def numbered(ranged: DataFrame) -> DataFrame:
    """A stream in order from partition to partition, with each row's place."""
    spark = ranged.sparkSession
    local = F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))
    stored = materialise(ranged.withColumn("_part", F.spark_partition_id()).withColumn("_at", local), "positions")
    counts = {r["_part"]: r["count"] for r in stored.groupBy("_part").count().collect()}
    size = max(counts, default=0) + 1
    before = np.concatenate([[0], np.cumsum([counts.get(k, 0) for k in range(size)])])[:size].tolist()
    base = spark.createDataFrame([(k, int(b)) for k, b in enumerate(before)], "_part int, _base long")
    # one row a partition: bounded by the number of partitions
    return stored.join(F.broadcast(base), "_part").withColumn("pos", F.col("_base") + F.col("_at")).drop("_part", "_at", "_base")


def zip_streams(a: DataFrame, b: DataFrame, how: str = "inner") -> DataFrame:
    """Two streams item by item, on pos."""
    return a.join(b.hint("merge"), "pos", how)
