"""Joins by strategy and by condition."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pipeflow.grid.shape import div

#: Rows that a side may have to be broadcast without the optimizer's own size check.
SMALL_ROWS = 1_000_000


def merge(left: DataFrame, right: DataFrame, on: str | list[str], how: str = "inner") -> DataFrame:
    """Two sorted streams read side by side."""
    return left.join(right.hint("merge"), on, how)


def broadcast(left: DataFrame, right: DataFrame, on: str | list[str] | Column, how: str = "inner", checked_rows: int | None = None) -> DataFrame:
    """right goes to every task if it has few rows (counted, unless checked_rows says so); else Spark chooses."""
    n = right.limit(SMALL_ROWS + 1).count() if checked_rows is None else checked_rows
    return left.join(F.broadcast(right) if n <= SMALL_ROWS else right, on, how)


def hashed(left: DataFrame, right: DataFrame, on: str | list[str], how: str = "inner") -> DataFrame:
    return left.join(right.hint("shuffle_hash"), on, how)


def theta(left: DataFrame, right: DataFrame, cond: Column) -> DataFrame:
    """Any condition: a nested loop over a small, counted right side."""
    return broadcast(left, right, cond)


def cross(left: DataFrame, right: DataFrame) -> DataFrame:
    if right.limit(SMALL_ROWS + 1).count() > SMALL_ROWS:
        raise ValueError("the right side of a cross product is too large")
    return left.crossJoin(F.broadcast(right))


def in_band(points: DataFrame, value: str, bands: DataFrame, low: str, high: str, width: float) -> DataFrame:
    """low <= value < high: bands are laid over bins of `width`, points meet the bands of their bin only."""
    b = bands.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    p = points.withColumn("_bin", F.floor(F.col(value) / width))
    return p.join(b, "_bin").where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("_bin")


def within(left: DataFrame, right: DataFrame, key: str, left_s: str, right_s: str, seconds: int) -> DataFrame:
    """right not before left and less than `seconds` after it, of one key. *_s: whole seconds."""
    a = left.withColumn("_slot", div(F.col(left_s), seconds))
    b = right.withColumn("_slot", F.explode(F.array(div(F.col(right_s), seconds), div(F.col(right_s), seconds) - 1)))
    return a.join(b, [key, "_slot"]).where((F.col(right_s) >= F.col(left_s)) & (F.col(right_s) < F.col(left_s) + seconds)).drop("_slot")


def asof(left: DataFrame, right: DataFrame, key: str, order: str, value: str, out: str, slot: Column | None = None) -> DataFrame:
    """left's rows with the value of the last right row of the same key at or before theirs. One shuffle: union and window.

    A key's rows make one task. Where a key may be hot, slot, an expression that never falls as `order` grows, cuts them:
    a slot's rows meet by themselves, and what earlier slots end with, one row a key and slot, is handed on to it.
    A null key or place has no partner; null values are passed over.
    """
    l_ = left.withColumn("_v", F.lit(None).cast(right.schema[value].dataType)).withColumn("_side", F.lit(1))
    blank = [F.lit(None).cast(f.dataType).alias(f.name) for f in left.schema.fields if f.name not in (key, order)]
    r_ = right.where(F.col(key).isNotNull() & F.col(order).isNotNull()).select(key, order, *blank, F.col(value).alias("_v"), F.lit(0).alias("_side"))
    line = l_.unionByName(r_).withColumn("_slot", F.lit(0) if slot is None else slot)
    w = Window.partitionBy(key, "_slot").orderBy(order, "_side").rowsBetween(Window.unboundedPreceding, 0)
    met = line.withColumn(out, F.last("_v", ignorenulls=True).over(w)).where("_side = 1").drop("_v", "_side")
    if slot is None:
        return met.drop("_slot")
    ends = line.groupBy(key, "_slot").agg(F.max_by(F.when(F.col("_v").isNotNull(), F.col("_v")), F.when(F.col("_v").isNotNull(), F.col(order))).alias("_end"))
    earlier = Window.partitionBy(key).orderBy("_slot").rowsBetween(Window.unboundedPreceding, -1)
    ends = ends.select(key, "_slot", F.last("_end", ignorenulls=True).over(earlier).alias("_end"))
    return met.join(ends.where("_end is not null"), [key, "_slot"], "left").withColumn(out, F.coalesce(out, "_end")).select(*left.columns, out)


def star(fact: DataFrame, dims: list[tuple[DataFrame, str]]) -> DataFrame:
    """A fact table and its dimensions; a dimension of few rows is broadcast."""
    for dim, on in dims:
        fact = broadcast(fact, dim, on)
    return fact


def merge_union(streams: list[DataFrame], key: list[str], parts: int) -> DataFrame:
    """Sorted streams as one sorted stream."""
    out = streams[0]
    for s in streams[1:]:
        out = out.unionByName(s)
    return out.repartitionByRange(parts, *key).sortWithinPartitions(*key)
