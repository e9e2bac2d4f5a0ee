"""Sources and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from pipeflow.grid.regrid import round_trip, save_clustered, write_grid
from pipeflow.session import fresh_path, materialise


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cells(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).withColumnRenamed("id", "cell")


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: list[str] = (), **options: str) -> None:
    w = df.write.format(fmt).options(**options)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def read(spark: SparkSession, path: str, fmt: str, schema=None, **options: str) -> DataFrame:
    r = spark.read.format(fmt).options(**options)
    return (r.schema(schema) if schema is not None else r).load(path)


def through(df: DataFrame, fmt: str, partition_by: list[str] = (), **options: str) -> DataFrame:
    """df written in a format and read back with its own schema."""
    path = fresh_path(df.sparkSession, fmt)
    write(df, path, fmt, partition_by, **options)
    return read(df.sparkSession, path, fmt, df.schema, **options).select(*df.columns)


def noop(df: DataFrame) -> None:
    """Everything is computed, nothing is kept."""
    df.write.format("noop").mode("overwrite").save()


__all__ = ["cells", "fresh_path", "materialise", "noop", "read", "round_trip", "save_clustered", "table", "through", "write", "write_grid"]
