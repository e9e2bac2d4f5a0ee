"""Row-major grids: the cell of (x, y) is y * width + x. Frames in cell form have the columns cell and v."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class GridShape:
    width: int
    height: int

    @property
    def n(self) -> int:
        return self.width * self.height

    def cell(self, x: Column, y: Column) -> Column:
        return (y * F.lit(self.width) + x).cast("long")

    def x(self, cell: Column) -> Column:
        return F.pmod(cell, F.lit(self.width).cast("long"))

    def y(self, cell: Column) -> Column:
        return div(cell, self.width)

    def holds(self, x: Column, y: Column) -> Column:
        return (x >= 0) & (x < self.width) & (y >= 0) & (y < self.height)


def div(a: Column, b: int | Column) -> Column:
    """Whole-number quotient of non-negative longs, without a detour over doubles."""
    b = F.lit(b).cast("long") if isinstance(b, int) else b
    return F.call_function("div", a, b)


def table_grid(spark: SparkSession, sf_dir: str, table: str, key: str, value: str, width: int) -> tuple[DataFrame, GridShape]:
    """A given table whose dense key is the cell number; what is short of a full last row stays out."""
    df = spark.read.parquet(f"{sf_dir}/{table}.parquet").select(F.col(key).cast("long").alias("cell"), F.col(value).alias("v"))
    height = df.count() // width
    return df.where(F.col("cell") < width * height), GridShape(width, height)


def to_tiles(a: DataFrame, size: int) -> DataFrame:
    """Cell form to tile form: tile, vals, an array of `size` cells in order (the last may be shorter)."""
    pairs = F.array_sort(F.collect_list(F.struct("cell", "v")))
    return a.groupBy(div(F.col("cell"), size).alias("tile")).agg(pairs.alias("p")).select("tile", F.col("p.v").alias("vals"))


def to_cells(tiles: DataFrame, size: int) -> DataFrame:
    return tiles.select("tile", F.posexplode("vals").alias("k", "v")).select((F.col("tile") * size + F.col("k")).alias("cell"), "v")
