"""Window operators and order."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def over(df: DataFrame, part: list[str], order: list[Column | str], **cols: Column) -> DataFrame:
    w = Window.partitionBy(*part).orderBy(*order)
    return df.select("*", *(c.over(w).alias(n) for n, c in cols.items()))


def rows(df: DataFrame, part: list[str], order: list[str], start: int, end: int, **cols: Column) -> DataFrame:
    w = Window.partitionBy(*part).orderBy(*order).rowsBetween(start, end)
    return df.select("*", *(c.over(w).alias(n) for n, c in cols.items()))


def ranged(df: DataFrame, part: list[str], order: str, start: int, end: int, **cols: Column) -> DataFrame:
    w = Window.partitionBy(*part).orderBy(order).rangeBetween(start, end)
    return df.select("*", *(c.over(w).alias(n) for n, c in cols.items()))


def prefix_sum(df: DataFrame, part: list[str], order: list[str], value: str, out: str) -> DataFrame:
    return rows(df, part, order, Window.unboundedPreceding, 0, **{out: F.sum(value)})


def sessions(df: DataFrame, key: str, seconds: str, gap: int, out: str = "session") -> DataFrame:
    """Number of each row's session of its key: a new one begins after `gap` seconds without a row."""
    w = Window.partitionBy(key).orderBy(seconds)
    new = (F.col(seconds) - F.lag(seconds).over(w) > gap).cast("int")
    return df.withColumn("_new", F.coalesce(new, F.lit(0))).withColumn(out, F.sum("_new").over(w.rowsBetween(Window.unboundedPreceding, 0))).drop("_new")


def topk_by(df: DataFrame, part: list[str], order: list[Column | str], k: int) -> DataFrame:
    """The window limits each group before and after the shuffle."""
    return over(df, part, order, _r=F.row_number()).where(F.col("_r") <= k).drop("_r")


def total(df: DataFrame, *keys: Column) -> DataFrame:
    return df.orderBy(*keys)


def local(df: DataFrame, *keys: str) -> DataFrame:
    return df.sortWithinPartitions(*keys)
