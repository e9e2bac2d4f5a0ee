"""Aggregates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def by(df: DataFrame, keys: list[str], **aggs: Column) -> DataFrame:
    return df.groupBy(*keys).agg(*(a.alias(n) for n, a in aggs.items()))


def segmented(stream: DataFrame, key: str, **aggs: Column) -> DataFrame:
    """Over a stream clustered by key: no exchange, one pass over each run of equal keys."""
    return by(stream, [key], **aggs)


def ordered_list(df: DataFrame, key: str, order: str, value: str, out: str) -> DataFrame:
    rows = F.array_sort(F.collect_list(F.struct(order, value)))
    return df.groupBy(key).agg(rows.alias("_r")).select(key, F.col(f"_r.{value}").alias(out))


def rollup(df: DataFrame, keys: list[str], **aggs: Column) -> DataFrame:
    return df.rollup(*keys).agg(*(a.alias(n) for n, a in aggs.items()))


def cube(df: DataFrame, keys: list[str], **aggs: Column) -> DataFrame:
    return df.cube(*keys).agg(*(a.alias(n) for n, a in aggs.items()))


def sets(df: DataFrame, groups: list[list[str]], keys: list[str], **aggs: Column) -> DataFrame:
    return df.groupingSets([[F.col(c) for c in g] for g in groups], *keys).agg(*(a.alias(n) for n, a in aggs.items()))


def pivot(df: DataFrame, keys: list[str], column: str, values: list[str], agg: Column) -> DataFrame:
    return df.groupBy(*keys).pivot(column, values).agg(agg)
