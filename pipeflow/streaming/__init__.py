"""Structured streaming over files: event-time windows, late rows, joins, state, pipelines per micro-batch.

Every function runs a stream over what there is (availableNow) and returns the result as a batch frame; the same plans
run with a processing-time trigger. Checkpoints lie in the shared folder.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor

from pipeflow.session import fresh_path


def source(spark: SparkSession, path: str, files_per_trigger: int | None = None) -> DataFrame:
    """A stream of a Parquet folder or file; event times become timestamps for watermarks."""
    schema = spark.read.parquet(path).schema
    r = spark.readStream.schema(schema)
    if files_per_trigger:
        r = r.option("maxFilesPerTrigger", files_per_trigger)
    # a single file is found by its pattern: streams watch folders
    df = r.parquet(path if not path.endswith(".parquet") else f"{path.rsplit('/', 1)[0]}/{path.rsplit('/', 1)[1][:-1]}*")
    return df


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return source(spark, f"{sf_dir}/events.parquet").withColumn("time", F.col("ts").cast("timestamp"))


def collect(df: DataFrame, mode: str = "append") -> DataFrame:
    """Runs the stream to its present end; rows land in a Parquet folder (append) or the last full result (complete)."""
    spark = df.sparkSession
    out = fresh_path(spark, "stream")
    writer = df.writeStream.option("checkpointLocation", fresh_path(spark, "stream-state")).trigger(availableNow=True)
    if mode == "append":
        query = writer.outputMode("append").format("parquet").option("path", out).start()
        query.awaitTermination()
    else:
        query = writer.outputMode(mode).foreachBatch(lambda b, i: b.write.mode("overwrite").parquet(out)).start()
        query.awaitTermination()
    return spark.read.schema(df.schema).parquet(out)


def windowed(stream: DataFrame, size: str, slide: str | None, keys: list[str], late: str = "1 hour") -> DataFrame:
    w = F.window("time", size, slide) if slide else F.window("time", size)
    return stream.withWatermark("time", late).groupBy(w, *keys).agg(F.count("*").alias("n"))


def sessions(stream: DataFrame, gap: str, key: str, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("time", late).groupBy(F.session_window("time", gap), key).agg(F.count("*").alias("n"))


def distinct(stream: DataFrame, keys: list[str], late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("time", late).dropDuplicatesWithinWatermark(keys)


def per_batch(stream: DataFrame, f: Callable[[DataFrame, int], DataFrame], schema) -> DataFrame:
    """f of each micro-batch, appended under the batch's own folder, so that a batch that runs again replaces itself."""
    spark = stream.sparkSession
    out = fresh_path(spark, "batches")
    query = stream.writeStream.option("checkpointLocation", fresh_path(spark, "stream-state")).trigger(availableNow=True).foreachBatch(lambda b, i: f(b, i).write.mode("overwrite").parquet(f"{out}/batch={i}")).start()
    query.awaitTermination()
    return spark.read.schema(schema).parquet(out).drop("batch")


class RunState(StatefulProcessor):
    """Rows and the sum of a value of each key: a component's buffer that outlives the micro-batch."""

    def init(self, handle) -> None:
        self.state = handle.getValueState("sums", "n long, total double")

    def handleInputRows(self, key, rows, timerValues):
        n, total = self.state.get() if self.state.exists() else (0, 0.0)
        for pdf in rows:
            n, total = n + len(pdf), total + float(pdf["value"].sum())
        self.state.update((n, total))
        yield pd.DataFrame({"event_type": [key[0]], "n": [n], "total": [total]})

    def close(self) -> None:
        pass


def stateful_sums(stream: DataFrame) -> DataFrame:
    return stream.groupBy("event_type").transformWithStateInPandas(statefulProcessor=RunState(), outputStructType="event_type string, n long, total double", outputMode="Update", timeMode="None")


def unique_name(prefix: str) -> str:
    return f"{prefix}_{uuid.uuid4().hex}"


def updates(df: DataFrame) -> DataFrame:
    """All updates of a stream in update mode, by micro-batch."""
    spark = df.sparkSession
    out = fresh_path(spark, "updates")
    query = df.writeStream.option("checkpointLocation", fresh_path(spark, "stream-state")).outputMode("update").trigger(availableNow=True).foreachBatch(lambda b, i: b.write.mode("overwrite").parquet(f"{out}/batch={i}")).start()
    query.awaitTermination()
    return spark.read.schema(df.schema).parquet(out)


def resume(df: DataFrame, out: str, state: str) -> int:
    """Runs the stream from where its checkpoint `state` stands to its present end; rows land in `out`. Rows read this time.

    After a failure or a stop the same call goes on: committed batches aren't read again, an uncommitted one is replaced.
    """
    q = df.writeStream.option("checkpointLocation", state).trigger(availableNow=True).format("parquet").outputMode("append").start(out)
    q.awaitTermination()
    return sum(p["numInputRows"] for p in q.recentProgress)
