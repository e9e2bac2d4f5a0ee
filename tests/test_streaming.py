import os

from pyspark.sql import functions as F

from pipeflow import streaming


def test_late_rows_are_dropped(spark, tmp_path):
    """The third file holds a row of a day that the watermark has passed: its window doesn't count it."""
    folder = str(tmp_path / "in")
    for k, days in enumerate((("2024-01-01", "2024-01-01", "2024-01-05"), ("2024-01-06",), ("2024-01-01", "2024-01-09"))):
        rows = spark.createDataFrame([(d,) for d in days], "d string").select(F.to_timestamp("d").alias("time"), F.lit("x").alias("kind"))
        rows.coalesce(1).write.mode("append").parquet(folder)
        for f in os.listdir(folder):
            if f.endswith(".parquet") and os.path.getmtime(f"{folder}/{f}") > 2_000_000:
                os.utime(f"{folder}/{f}", (1_000_000 + k * 1000,) * 2)
    stream = streaming.source(spark, folder, files_per_trigger=1)
    out = streaming.collect(streaming.windowed(stream, "1 day", None, ["kind"]).select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "n"))
    assert {(r.day, r.n) for r in out.collect()} == {("2024-01-01", 2), ("2024-01-05", 1), ("2024-01-06", 1)}


def test_batches_that_run_again_replace_themselves(spark, tmp_path):
    folder = str(tmp_path / "in")
    spark.range(10).write.parquet(folder)
    parts = streaming.per_batch(streaming.source(spark, folder), lambda b, i: b.groupBy().count(), "count long, batch int")
    assert [r["count"] for r in parts.collect()] == [10]


def test_a_stream_restarts_from_its_checkpoint(spark, tmp_path):
    folder, out, state = (str(tmp_path / x) for x in ("in", "out", "state"))
    spark.range(10).write.parquet(folder)
    assert streaming.resume(streaming.source(spark, folder), out, state) == 10
    spark.range(10, 15).write.mode("append").parquet(folder)
    assert streaming.resume(streaming.source(spark, folder), out, state) == 5
    assert streaming.resume(streaming.source(spark, folder), out, state) == 0
    assert sorted(r.id for r in spark.read.parquet(out).collect()) == list(range(15))
