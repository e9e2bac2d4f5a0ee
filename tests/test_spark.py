import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from pipeflow.grid import mappings as maps
from pipeflow.grid import regrid
from pipeflow.grid.shape import GridShape, to_cells, to_tiles
from pipeflow.operators import joins
from pipeflow.plans import cost, memory, metrics, parallel, phases, pipeline, progress
from pipeflow.plans.graph import FlowGraphError, delay_graph, regrid_graph
from pipeflow.session import fresh_path
from pipeflow.streams import extsort
from pipeflow.streams.ordered import OrderedStream, with_positions


def grid(spark, s):
    return spark.range(s.n).select(F.col("id").alias("cell"), (F.col("id") * 1.5).alias("v"))


def values(df):
    return [r.v for r in sorted(df.collect(), key=lambda r: r.tgt)]


METHODS = {
    "fused": regrid.fused, "direct": regrid.direct, "plain": regrid.plain_sql, "clustered": regrid.clustered, "staged": regrid.staged, "handmade": regrid.handmade_phases,
    "manual": lambda a, f: regrid.manual(a, f, 1 << 20, 1 << 10, 1 << 10), "tiled": lambda a, f: regrid.tiled(a, f, 3), "pruned": lambda a, f: regrid.tile_pruned(a, f, 3),
    "pipeline": lambda a, f: next(iter(pipeline.regrid(a, f).run(a.sparkSession)[0].values())),
}


@pytest.mark.parametrize("name", METHODS)
def test_every_method_transposes(spark, name):
    s = GridShape(7, 3)
    want = (np.arange(21) * 1.5).reshape(3, 7).T.ravel().tolist()
    assert values(METHODS[name](grid(spark, s), maps.transpose(s))) == want


def test_direct_broadcasts_small_sources_only(spark):
    def plan(s):
        return regrid.direct(grid(spark, s), maps.transpose(s))._jdf.queryExecution().executedPlan().toString()

    assert "BroadcastHashJoin" in plan(GridShape(100, 10)) and "Broadcast" not in plan(GridShape(100, 90_000))


@pytest.mark.parametrize(("w", "h"), [(1, 1), (1, 5), (5, 1), (4, 4), (3, 0)])
def test_edge_shapes(spark, w, h):
    s = GridShape(w, h)
    a = grid(spark, s)
    assert values(regrid.fused(a, maps.transpose(s))) == (np.arange(w * h) * 1.5).reshape(h, w).T.ravel().tolist()


def test_off_grid_policies(spark):
    s = GridShape(4, 3)
    f = maps.shift(s, 1, 1)
    a = grid(spark, s)
    assert values(regrid.fused(a, f)) == [None] * 5 + [0.0, 1.5, 3.0, None, 6.0, 7.5, 9.0]
    assert regrid.fused(a, f, "drop").count() == 6
    with pytest.raises(Exception, match="off the source grid"):
        regrid.fused(a, f, "error").collect()


def test_hot_source_cell(spark):
    s = GridShape(10, 10)
    f = maps.CellMap("constant", s, s, lambda t: F.lit(5).cast("long"))
    assert set(values(regrid.fused(grid(spark, s), f))) == {7.5}


def test_double_transpose_and_rotations(spark):
    s = GridShape(5, 4)
    a = grid(spark, s)
    once = regrid.fused(a, maps.rotate90(s)).withColumnRenamed("tgt", "cell")
    assert values(regrid.fused(once, maps.rotate270(GridShape(4, 5)))) == [1.5 * i for i in range(20)]
    assert values(regrid.fused(a, maps.rotate90(s))) == np.rot90(np.arange(20).reshape(4, 5) * 1.5, -1).ravel().tolist()


def test_tiles_round_trip(spark):
    a = grid(spark, GridShape(7, 3))
    back = to_cells(to_tiles(a, 4), 4)
    assert sorted(map(tuple, back.collect())) == sorted(map(tuple, a.collect()))


def test_fused_plan_has_two_sorts_and_no_sampling(spark):
    s = GridShape(50, 40)
    text = metrics.plan_text(regrid.fused(grid(spark, s), maps.transpose(s)), "simple")
    assert "SortMergeJoin" in text and "rangepartitioning" not in text and "Parquet" not in text
    assert metrics.codegen_spans(regrid.fused(grid(spark, s), maps.transpose(s))) >= 1


def test_measured_traffic_of_clustered_fusion(spark):
    s = GridShape(50, 40)
    n = s.n
    name = regrid.save_clustered(grid(spark, s), "cell", 4)
    df = regrid.fused(spark.table(name), maps.transpose(s), "drop")
    group = metrics.run_in_group(spark, lambda: df.write.parquet(fresh_path(spark, "out")))
    rows = metrics.stage_traffic(spark, group).collect()
    assert sum(r.shuffle_write for r in rows) == 2 * n and sum(r.shuffle_read for r in rows) == 2 * n and sum(r.out_records for r in rows) == n


def test_predicted_traffic(spark):
    for mode, total in (("staged", (7, 7)), ("fused", (3, 3))):
        r = cost.item_traffic(spark, 10, mode).agg(F.sum("reads"), F.sum("writes")).first()
        assert tuple(r) == (total[0] * 10, total[1] * 10)


def lru(trace, b, k):
    held, misses = [], 0
    for c in trace:
        x = c // b
        if x in held:
            held.remove(x)
        else:
            misses += 1
            held = held[-(k - 1) :] if k > 1 else []
        held.append(x)
    return misses


@pytest.mark.parametrize("cache", [1, 3, 20])
def test_block_transfers(spark, cache):
    s = GridShape(20, 20)
    order = [(t % 20) * 20 + t // 20 for t in range(400)]
    trace = regrid.pairs(spark, maps.transpose(s)).select(F.col("tgt").alias("pos"), F.col("src").alias("cell"))
    got = cost.count_block_ios(trace, 10, cache, chunk=64 if cache == 1 else 1 << 20).first()
    assert (got.n, got.ios) == (400, lru(order, 10, cache))


@pytest.mark.parametrize(("cache", "chunk"), [(3, 7), (20, 64), (25, 10), (50, 1)])
def test_block_transfers_over_seams(spark, cache, chunk):
    s = GridShape(20, 20)
    order = [(t % 20) * 20 + t // 20 for t in range(400)]
    trace = regrid.pairs(spark, maps.transpose(s)).select(F.col("tgt").alias("pos"), F.col("src").alias("cell"))
    got = cost.count_block_ios(trace, 10, cache, chunk=chunk).first()
    assert (got.n, got.ios) == (400, lru(order, 10, cache))
    r = np.random.default_rng(cache)
    order = r.integers(0, 400, 300).tolist()
    got = cost.count_block_ios(spark.createDataFrame(list(enumerate(order)), "pos long, cell long"), 10, cache, chunk=chunk).first()
    assert (got.n, got.ios) == (300, lru(order, 10, cache))


def test_pipeline_runs_in_every_mode(spark):
    s = GridShape(6, 4)
    want = (np.arange(24) * 1.5).reshape(4, 6).T.ravel().tolist()
    store = progress.ProgressStore(spark, fresh_path(spark, "progress"))
    for mode in ("fused", "by_phase", "materialised"):
        p = pipeline.regrid(grid(spark, s), maps.transpose(s))
        out, report = p.run(spark, mode=mode, size=48, store=store, identity="here", action=lambda df: df.count())
        assert values(next(iter(out.values()))) == want and [len(x) for x in report.phases] == [3, 4, 3]
        assert report.progress == sorted(report.progress) and report.progress[-1] == pytest.approx(1)
        assert pipeline.component_count(p) == 8
        assert [n for h, n in report.hooks if h == "drive"] == ["src", "rd", "S2o"]
    assert sum(store.shares("here")) == pytest.approx(1) and store.shares("elsewhere") is None


def test_largest_run_gives_the_shares(spark):
    store = progress.ProgressStore(spark, fresh_path(spark, "progress"))
    store.record("p", "1", 10, [1, 1], [5, 5])
    store.record("p", "2", 99, [3, 1], [5, 5])
    store.record("p", "3", 20, [1, 9], [5, 5])
    assert store.shares("p") == [0.75, 0.25]


def test_metadata_and_parallel_rules(spark):
    s = GridShape(2, 2)
    p = pipeline.regrid(grid(spark, s), maps.identity(s))
    run = pipeline.Run(p)
    assert run.lookup("co", "target") == s
    with pytest.raises(pipeline.MetadataError):
        run.lookup("rd", "target")
    pulled = pipeline.Sort("cell", name="S").pulled()
    scan = pipeline.parallel(pipeline.Map(lambda d: d, "f"))
    bad = pipeline.Pipeline(pipeline.Source(grid(spark, s), "a") | pulled.input, pipeline.Source(grid(spark, s), "b") | scan, extra=[(pulled.output, scan)])
    with pytest.raises(FlowGraphError):
        bad.run(spark)


def test_deal(spark):
    df = spark.range(10_000).withColumnRenamed("id", "pos")
    got = parallel.deal(df, "pos", 4).groupBy(F.spark_partition_id().alias("w")).count().collect()
    assert sorted(r["count"] for r in got) == [2048, 2048, 2048, 3856]


def test_bulk_phases_agree_with_the_driver(spark):
    nodes, edges = [], []
    for k, g in enumerate((regrid_graph(), phases.insert_delays(delay_graph()))):
        nodes += [(k, n.name, n.kind, n.block) for n in g.nodes]
        edges += [(k, e.src, e.dst, e.kind) for e in g.edges]
    n = spark.createDataFrame(nodes, "graph int, node string, kind string, block string")
    e = spark.createDataFrame(edges, "graph int, src string, dst string, kind string")
    got = phases.identify_df(n, e)
    levels = {(r.graph, r.phase): r.level for r in phases.order_df(got, e).collect()}
    want = phases.identify(regrid_graph())
    mine = {r.node: levels[(0, r.phase)] + 1 for r in got.where("graph = 0").collect()}
    assert mine == want and phases.violations_df(n, e).count() == 0
    g = delay_graph()
    n = spark.createDataFrame([(0, x.name, x.kind, x.block) for x in g.nodes], n.schema)
    e = spark.createDataFrame([(0, x.src, x.dst, x.kind) for x in g.edges], e.schema)
    assert [(r.rule, r.node) for r in phases.violations_df(n, e).collect()] == [("self_blocked", "Si")]


def test_bulk_memory_agrees_with_the_driver(spark):
    r = random.Random(3)
    rows = [(p, i, r.randint(0, 20), r.choice([None, 40, 60]), r.randint(1, 5)) for p in range(6) for i in range(7)]
    rows += [(9, 0, 1, 2, 1), (9, 1, 1, 3, 1), (8, 0, 50, None, 1)]
    budget = {p: 2 * sum(x[2] for x in rows if x[0] == p) + 5 for p in range(6)} | {9: 100, 8: 10}
    asks = spark.createDataFrame(rows, "phase int, node int, lo long, hi long, prio long")
    got = {(x.phase, x.node): x.assigned for x in memory.assign_df(asks, spark.createDataFrame(list(budget.items()), "phase int, available long")).collect()}
    for p in budget:
        mine = {str(i): memory.MemoryAsk(lo, float("inf") if hi is None else hi, c) for q, i, lo, hi, c in rows if q == p}
        if p == 8:
            assert got[(8, 0)] is None
            continue
        for i, v in memory.assign(mine, budget[p])[1].items():
            assert got[(p, int(i))] == pytest.approx(v)


def test_external_sort(spark):
    r = random.Random(1)
    rows = [(i, r.randint(0, 99)) for i in range(300)]
    s = spark.createDataFrame(rows, "pos long, k long")
    out = extsort.external_sort(s, ["k", "pos"], 20, 3)
    assert out.select("run_id").distinct().count() == 1
    assert [x.k for x in with_positions(out.drop("pos"), "k").orderBy("pos").collect()] == sorted(k for _, k in rows)
    assert extsort.run_stats(extsort.form_runs(s, 20), "k").count() == 15


def test_reverse_twice(spark):
    s = OrderedStream(spark.range(20).select(F.col("id").alias("pos"), (F.col("id") * 2).alias("x")), ("pos",))
    back = s.reverse(20).reverse(20).delay().df
    assert sorted(map(tuple, back.collect())) == [(i, 2 * i) for i in range(20)]


@pytest.mark.parametrize("width", [None, 1, 7, 1000])
def test_asof_against_loops(spark, width):
    r = random.Random(3)
    keys = [0] * 6 + [1, 2, None]  # one key holds most rows
    left = [(i, r.choice(keys), r.choice([None, *range(60)]), "x") for i in range(150)]
    right = [(r.choice(keys), t, r.choice([None, t * 10])) for t in r.sample(range(60), 40)] + [(0, None, 5)]
    a = spark.createDataFrame(left, "id long, k long, t long, note string")
    b = spark.createDataFrame(right, "k long, t long, v long")
    slot = None if width is None else F.floor(F.col("t") / width)
    got = joins.asof(a, b, "k", "t", "v", "last", slot)
    assert got.columns == ["id", "k", "t", "note", "last"]
    want = {}
    for i, k, t, _ in left:
        met = [(s, v) for q, s, v in right if None not in (k, t, s, v) and q == k and s <= t]
        want[i] = max(met)[1] if met else None
    assert {x.id: x.last for x in got.collect()} == want


def test_align_types_and_missing_cells(spark):
    s = GridShape(7, 4)
    a, b = grid(spark, s), spark.range(0, s.n, 2).select(F.col("id").alias("cell"), F.col("id").cast("string").alias("v"))
    crop = maps.CellMap("crop", s, s, lambda t: F.when(t < 10, t))
    out = regrid.align([(a, maps.rotate180(s)), (b, maps.identity(s)), (a, crop)])
    assert out.schema["v2"].dataType.simpleString() == "string"
    got = sorted((x.cell, x.v1, x.v2, x.v3) for x in out.collect())
    assert got == [(c, (s.n - 1 - c) * 1.5, str(c) if c % 2 == 0 else None, c * 1.5 if c < 10 else None) for c in range(s.n)]


def test_extrapolated_merges(spark):
    """One pass by the published example; 125 runs by fives are three passes, though log(125) / log(5) lies above 3; one run needs none."""
    jobs = spark.createDataFrame([(1e12, 1e9, 1e6), (125.0, 1.0, 0.2), (10.0, 100.0, 1.0)], "n double, m double, b double").withColumn("item", F.lit(1)).withColumn("speed", F.when(F.col("n") > 1e6, 1e8).otherwise(F.col("n") / 3600))
    got = {r.runs: (r.merges, r.staged_h, r.fused_h, r.saved_h) for r in cost.extrapolate(jobs).collect()}
    assert got == {1000: (1, 38.8889, 16.6667, 22.2222), 125: (3, 22, 14, 8), 1: (0, 10, 2, 8)}
