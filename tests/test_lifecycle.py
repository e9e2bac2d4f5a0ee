"""Hooks, ticks, seconds and memory of runs that really stream."""

import re
import time

import pytest
from pyspark.sql import functions as F

from pipeflow.grid import mappings as maps
from pipeflow.grid.shape import GridShape
from pipeflow.plans import pipeline, progress
from pipeflow.plans.ports import Items
from pipeflow.session import fresh_path


def slow(seconds):
    def run(batches):
        for b in batches:
            time.sleep(seconds)
            yield b

    return lambda df: df.repartition(16).mapInArrow(run, df.schema)


def test_ticks_lie_inside_a_running_phase(spark):
    for mode in ("by_phase", "fused"):
        chain = pipeline.Source(spark.range(4000), "read") | pipeline.Map(slow(0.15), "slow") | pipeline.Sort("id", name="S") | pipeline.Map(lambda d: d, "give")
        out, report = pipeline.Pipeline(chain).run(spark, mode=mode, action=lambda df: df.count())
        values = [x for _, x in report.ticks]
        assert values and values == sorted(values) and all(0 < x < 1 for x in values)
        if mode == "by_phase":
            assert any(0 < x < 0.5 for k, x in report.ticks if k == 0)
        assert report.progress[-1] == pytest.approx(1) and sum(report.seconds) > 0.3


class Noted(pipeline.Map):
    def __init__(self, name, log):
        super().__init__(lambda d: d, name)
        self.log = log

    def open(self, ctx):
        self.log.append(("open", self.name))

    def close(self, ctx):
        self.log.append(("close", self.name))


@pytest.mark.parametrize("mode", ["fused", "by_phase"])
def test_hooks_frame_what_streams(spark, mode):
    log = []
    chain = pipeline.Source(spark.range(100), "read") | Noted("a", log) | pipeline.Sort("id", name="S") | Noted("b", log)
    pipeline.Pipeline(chain).run(spark, mode=mode, action=lambda df: log.append(("streamed", df.count())))
    assert log.index(("open", "b")) < log.index(("streamed", 100)) < log.index(("close", "b"))
    if mode == "fused":
        assert log == [("open", "a"), ("open", "b"), ("streamed", 100), ("close", "a"), ("close", "b")]


def test_the_slow_phase_has_most_of_the_time_in_either_mode(spark):
    for mode in ("fused", "by_phase"):
        chain = pipeline.Source(spark.range(4000), "read") | pipeline.Map(slow(0.2), "slow") | pipeline.Sort("id", name="S") | pipeline.Map(lambda d: d, "give")
        report = pipeline.Pipeline(chain).run(spark, mode=mode, action=lambda df: df.write.format("noop").mode("overwrite").save())[1]
        assert len(report.seconds) == 2 and report.seconds[0] > 0.5 * sum(report.seconds), (mode, report.seconds)


def test_twice_the_share_halves_the_partitions(spark):
    def parts(k):
        chain = pipeline.Source(spark.range(10**9), "read") | pipeline.Sort("id", name="A") | pipeline.Sort("id", name="B")
        p = pipeline.Pipeline(chain)
        a, b = p.by_node["Ao"][0], p.by_node["Bi"][0]
        a.output.priority(k)
        b.input.priority(3)
        seen = {}
        real = a.plan_out
        a.plan_out = lambda ctx, stored: seen.setdefault("out", real(ctx, stored))
        p.run(spark, memory=400 << 20)
        return int(re.search(r"RepartitionByExpression .*, (\d+)", seen["out"]._jdf.queryExecution().analyzed().toString())[1])

    few = parts(3)
    assert few > 4 and abs(parts(1) - 2 * few) <= 2


@pytest.mark.parametrize("fmt", ["parquet", "orc", "json", "csv"])
def test_grids_are_read_and_written_by_format(spark, fmt):
    path, s = fresh_path(spark, "grid"), GridShape(4, 3)
    spark.range(12).select(F.col("id").alias("cell"), (F.col("id") * 0.5).alias("v")).write.format(fmt).save(path)
    p = pipeline.regrid(spark.range(0).select(F.col("id").alias("cell"), F.lit(0.0).alias("v")), maps.transpose(s))
    out = pipeline.GridWriter("wr", fresh_path(spark, "out"), fmt)
    p.by_node["rd"] = (pipeline.GridReader.from_file(spark, path, fmt, "rd"), "regular")
    p.by_node["wr"] = (out, "regular")
    got = next(iter(p.run(spark)[0].values()))
    assert [r.v for r in got.orderBy("tgt").collect()] == [0.5 * ((t % 3) * 4 + t // 3) for t in range(12)]


def test_ports(spark):
    def pairs(pull, push):
        a = pull.take()["id"]
        push.deliver({"low": a, "high": pull.take()["id"] if pull.more() else None})

    chain = pipeline.Source(spark.range(0, 101, 1, 1), "read") | Items(pairs, "low long, high long", "pairs", batch=7)
    rows = next(iter(pipeline.Pipeline(chain).run(spark)[0].values())).orderBy("low").collect()
    assert [(r.low, r.high) for r in rows] == [(k, k + 1 if k < 100 else None) for k in range(0, 101, 2)]


def test_unknown_pipelines_have_no_history(spark):
    assert progress.ProgressStore(spark, fresh_path(spark, "none")).shares("x") is None
