"""Projection, predicates, fan-out, unions and set operations."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def project(df: DataFrame, *keep: str, **exprs: Column) -> DataFrame:
    return df.select(*keep, *(e.alias(n) for n, e in exprs.items()))


def keep(df: DataFrame, cond: Column | str) -> DataFrame:
    return df.where(cond)


def fan(df: DataFrame, array: str, position: str = "k", item: str = "item") -> DataFrame:
    """One row an element: a component that gives several items for one."""
    return df.select("*", F.posexplode(array).alias(position, item)).drop(array)


def case(value: Column, cases: dict, otherwise: object = None) -> Column:
    out = reduce(lambda c, kv: c.when(value == kv[0], kv[1]), cases.items(), F)
    return out.otherwise(otherwise)


def sample(df: DataFrame, fraction: float, seed: int) -> DataFrame:
    return df.sample(fraction=fraction, seed=seed)


def union(*dfs: DataFrame) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), dfs)


def union_distinct(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b).distinct()


def intersect(a: DataFrame, b: DataFrame, every: bool = False) -> DataFrame:
    return a.intersectAll(b) if every else a.intersect(b)


def subtract(a: DataFrame, b: DataFrame, every: bool = False) -> DataFrame:
    return a.exceptAll(b) if every else a.subtract(b)
