"""The experiments on the given tables: regridding in all variants, traffic, phases, memory, progress, sorting."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from functools import partial

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pipeflow.grid import mappings as maps
from pipeflow.grid import regrid
from pipeflow.grid.shape import GridShape, div, table_grid
from pipeflow.plans import cost, memory, metrics, order, phases, pipeline, progress
from pipeflow.plans.graph import PULL, PUSH, Edge, FlowGraph
from pipeflow.plans.parallel import worker_of
from pipeflow.registry import add, query
from pipeflow.session import fresh_path, materialise
from pipeflow.sources import table
from pipeflow.streams import extsort
from pipeflow.streams.ordered import numbered, with_positions, zip_streams

GRIDS = {"orders": ("o_orderkey", "o_totalprice", 100), "events": ("event_id", "value", 100), "part": ("p_partkey", "p_retailprice", 50)}


def grid(spark: SparkSession, sf_dir: str, name: str, value: str | None = None) -> tuple[DataFrame, GridShape]:
    key, v, width = GRIDS[name]
    return table_grid(spark, sf_dir, name, key, value or v, width)


def by_blocks(df: DataFrame, key: str, size: int, columns: list[str], each: Callable[[int, list[tuple]], list[tuple]], schema: str) -> DataFrame:
    """Rows with equal key div size meet, in the order of key; `each` turns (block, [(key, *columns)]) into rows of schema, in the tasks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        to = pa.schema([(n, {"long": pa.int64(), "int": pa.int32(), "double": pa.float64(), "string": pa.string()}[k]) for n, k in (x.split() for x in schema.split(", "))])
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                rows = [r for block, items in zip(part["block"].to_pylist(), part["items"].to_pylist(), strict=True) for r in each(block, [tuple(i.values()) for i in items])]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), to.types, strict=True)] if rows else [pa.array([], t) for t in to.types], schema=to)

    met = df.groupBy(div(F.col(key), size).alias("block")).agg(F.sort_array(F.collect_list(F.struct(key, *columns))).alias("items"))
    return met.mapInArrow(run, schema)


# Regridding by every mapping, and by every method

#: name -> mapping of a shape, and SQL for the source cell of target cell t (null off the grid), target cells as n_t.
MAPPINGS = {
    "identity": (maps.identity, "n", "t"),
    "flip_x": (maps.flip_x, "n", "(t // w) * w + w - 1 - t % w"),
    "flip_y": (maps.flip_y, "n", "(h - 1 - t // w) * w + t % w"),
    "rot90": (maps.rotate90, "n", "(h - 1 - t % h) * w + t // h"),
    "rot180": (maps.rotate180, "n", "n - 1 - t"),
    "rot270": (maps.rotate270, "n", "(t % h) * w + w - 1 - t // h"),
    "shift": (lambda s: maps.shift(s, 7, 3), "n", "CASE WHEN t % w >= 7 AND t // w >= 3 THEN (t // w - 3) * w + t % w - 7 END"),
    "roll": (lambda s: maps.roll(s, 7, 3), "n", "((t // w - 3 + h) % h) * w + (t % w - 7 + w) % w"),
    "upscale": (lambda s: maps.upscale(s, 2), "4 * n", "(t // (2 * w) // 2) * w + (t % (2 * w)) // 2"),
    "downscale": (lambda s: maps.downscale(s, 2), "(w // 2) * (h // 2)", "(t // (w // 2)) * 2 * w + (t % (w // 2)) * 2"),
    "affine": (lambda s: maps.affine(s, (3, 1, 0), (1, 2, 0), 4), "n", "CASE WHEN (3 * (t % w) + t // w) // 4 < w AND (t % w + 2 * (t // w)) // 4 < h THEN ((t % w + 2 * (t // w)) // 4) * w + (3 * (t % w) + t // w) // 4 END"),
    "scatter": (lambda s: maps.scatter(s, 7919, 13), "n", "(t * 7919 + 13) % n"),
    "transpose": (maps.transpose, "n", "(t % h) * w + t // h"),
}


def regrid_sql(name: str, n_t: str, src: str) -> str:
    key, v, width = GRIDS[name]
    return f"""
WITH s AS (SELECT {width}::BIGINT AS w, count(*) // {width} AS h, (count(*) // {width}) * {width} AS n FROM {name}),
cells AS (SELECT unnest(range({n_t})) AS t, w, h, n FROM s),
pairs AS (SELECT CAST(t AS BIGINT) AS tgt, CAST({src} AS BIGINT) AS src FROM cells)
SELECT p.tgt, a.{v} AS v FROM pairs p LEFT JOIN {name} a ON a.{key} = p.src
"""


def regrid_case(spark: SparkSession, sf_dir: str, name: str, mapping: str, method: str) -> DataFrame:
    a, s = grid(spark, sf_dir, name)
    f = MAPPINGS[mapping][0](s)
    m = {
        "fused": regrid.fused, "direct": regrid.direct, "staged": regrid.staged, "handmade": regrid.handmade_phases, "clustered": regrid.clustered, "plain": regrid.plain_sql,
        "tiled": partial(regrid.tiled, tile=500), "tile_pruned": partial(regrid.tile_pruned, tile=500), "manual": partial(regrid.manual, memory=1 << 30, read_buffer=1 << 20, write_buffer=1 << 20),
        "pipeline": lambda a, f: next(iter(pipeline.regrid(a, f).run(spark)[0].values())),
    }[method]
    return m(a, f)


for _m, (_, _n, _src) in MAPPINGS.items():
    if _m != "transpose":
        add(f"regrid_fused_{_m}_orders", partial(regrid_case, name="orders", mapping=_m, method="fused"), regrid_sql("orders", _n, _src))
for _t in ("orders", "events", "part"):
    add(f"transpose_fused_{_t}", partial(regrid_case, name=_t, mapping="transpose", method="fused"), regrid_sql(_t, *MAPPINGS["transpose"][1:]))
for _x in ("direct", "staged", "handmade", "manual", "pipeline", "tiled", "tile_pruned", "clustered", "plain"):
    add(f"regrid_{_x}_transpose_orders", partial(regrid_case, name="orders", mapping="transpose", method=_x), regrid_sql("orders", *MAPPINGS["transpose"][1:]))
for _x in ("tiled", "tile_pruned"):
    add(f"regrid_{_x}_affine_orders", partial(regrid_case, name="orders", mapping="affine", method=_x), regrid_sql("orders", *MAPPINGS["affine"][1:]))


@query("transpose_fused_embeddings", "SELECT CAST((i - 1) * h.n + vec_id AS BIGINT) AS tgt, CAST(embedding[i] AS DOUBLE) AS v FROM embeddings, range(1, 65) r(i), (SELECT count(*) AS n FROM embeddings) h")
def transpose_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings")
    a = rows.select("vec_id", F.posexplode("embedding").alias("k", "x")).select((F.col("vec_id") * 64 + F.col("k")).alias("cell"), F.col("x").cast("double").alias("v"))
    return regrid.fused(a, maps.transpose(GridShape(64, rows.count())))


SPHERE = {
    "sinusoidal": ("lon * cos(lat) / (2 * pi()) + 0.5::DOUBLE", "0.5::DOUBLE - lat / pi()"),
    "mercator": ("lon / (2 * pi()) + 0.5::DOUBLE", "0.5::DOUBLE - ln(tan(lat / 2 + pi() / 4)) / (2 * pi())"),
    "laea": ("sqrt(2.0::DOUBLE / (1.0::DOUBLE + cos(lat) * cos(lon))) * cos(lat) * sin(lon) / 4 + 0.5::DOUBLE", "0.5::DOUBLE - sqrt(2.0::DOUBLE / (1.0::DOUBLE + cos(lat) * cos(lon))) * sin(lat) / 4"),
    "stereographic": ("2.0::DOUBLE / (1.0::DOUBLE + cos(lat) * cos(lon)) * cos(lat) * sin(lon) / 4 + 0.5::DOUBLE", "0.5::DOUBLE - 2.0::DOUBLE / (1.0::DOUBLE + cos(lat) * cos(lon)) * sin(lat) / 4"),
    "equirectangular": ("lon / (2 * pi()) + 0.5::DOUBLE", "0.5::DOUBLE - lat / pi()"),
}


def sphere_sql(u: str, v: str) -> str:
    return f"""
WITH s AS (SELECT 100::BIGINT AS w, count(*) // 100 AS h FROM orders),
cells AS (SELECT unnest(range(w * h)) AS t, w, h FROM s),
plane AS (SELECT t, w, h, ((t % w + 0.5::DOUBLE) / w - 0.5::DOUBLE) * (2 * pi()) AS lon, (0.5::DOUBLE - (t // w + 0.5::DOUBLE) / h) * pi() AS lat FROM cells),
image AS (SELECT t, w, h, CAST(floor(({u}) * w) AS BIGINT) AS x, CAST(floor(({v}) * h) AS BIGINT) AS y FROM plane)
SELECT CAST(t AS BIGINT) AS tgt, CASE WHEN x >= 0 AND x < w AND y >= 0 AND y < h THEN CAST(y * w + x AS BIGINT) END AS src FROM image
"""


def sphere_case(spark: SparkSession, sf_dir: str, source: str) -> DataFrame:
    """The source cell of every target cell, read as the value of a grid of cell numbers."""
    _, s = grid(spark, sf_dir, "orders")
    a = spark.range(s.n).select(F.col("id").alias("cell"), F.col("id").alias("v"))
    return regrid.fused(a, maps.through_sphere(s, source)).withColumnRenamed("v", "src")


for _p, _uv in SPHERE.items():
    add(f"regrid_sphere_{_p}", partial(sphere_case, source=_p), sphere_sql(*_uv))


@query("direct_ios_transpose", "WITH s AS (SELECT count(*) // 100 AS h, (count(*) // 100) * 100 AS n FROM orders), t AS (SELECT unnest(range(n)) AS t, h FROM s), b AS (SELECT t, ((t % h) * 100 + t // h) // 10 AS b FROM t), l AS (SELECT b, lag(b) OVER (ORDER BY t) AS p FROM b) SELECT count(*) AS n, CAST(count(*) FILTER (WHERE p IS NULL OR p != b) AS BIGINT) AS ios FROM l")
def direct_ios(spark: SparkSession, sf_dir: str, b: int = 10, cache: int = 1) -> DataFrame:
    _, s = grid(spark, sf_dir, "orders")
    trace = regrid.pairs(spark, maps.transpose(s)).select(F.col("tgt").alias("pos"), F.col("src").alias("cell"))
    return cost.count_block_ios(trace, b, cache, chunk=1 << 12 if cache == 1 else 1 << 20)


@query("direct_ios_transpose_cached")
def direct_ios_cached(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tested against a brute-force cache, over chunk seams too: tests/test_spark.py."""
    return direct_ios(spark, sf_dir, 10, 100)


@query("align_three_grids", "WITH s AS (SELECT least((SELECT count(*) FROM orders), (SELECT count(*) FROM events)) // 100 AS h, (SELECT count(*) // 100 FROM orders) AS ho) SELECT CAST(c.cell AS BIGINT) AS cell, a.o_totalprice AS v1, b.o_custkey AS v2, e.value AS v3 FROM (SELECT unnest(range(ho * 100)) AS cell, ho FROM s) c LEFT JOIN orders a ON a.o_orderkey = c.cell LEFT JOIN orders b ON b.o_orderkey = c.ho * 100 - 1 - c.cell LEFT JOIN events e ON e.event_id = c.cell AND c.cell < (SELECT (count(*) // 100) * 100 FROM events)")
def align_three(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, s = grid(spark, sf_dir, "orders")
    b, _ = grid(spark, sf_dir, "orders", "o_custkey")
    e, se = grid(spark, sf_dir, "events")
    as_orders = maps.CellMap("crop", se, s, lambda t: F.when(t < se.n, t))
    return regrid.align([(a, maps.identity(s)), (b, maps.rotate180(s)), (e, as_orders)])


# Traffic and time


def traffic_case(spark: SparkSession, sf_dir: str, mode: str) -> DataFrame:
    n = table(spark, sf_dir, "orders").count()
    return cost.item_traffic(spark, n, mode)


add("traffic_staged", partial(traffic_case, mode="staged"), "SELECT CAST(step AS INTEGER) AS step, CAST(phase AS INTEGER) AS phase, CAST(sum(r * n) AS BIGINT) AS reads, CAST(sum(w * n) AS BIGINT) AS writes FROM (VALUES (1, 1, 0, 1), (2, 1, 1, 1), (2, 2, 1, 1), (3, 2, 2, 1), (4, 2, 1, 1), (4, 3, 1, 1), (5, 3, 1, 1)) v(step, phase, r, w), (SELECT count(*) AS n FROM orders) GROUP BY step, phase")
add("traffic_fused", partial(traffic_case, mode="fused"), "SELECT CAST(step AS INTEGER) AS step, CAST(phase AS INTEGER) AS phase, CAST(sum(r * n) AS BIGINT) AS reads, CAST(sum(w * n) AS BIGINT) AS writes FROM (VALUES (1, 1, 0, 0), (2, 1, 0, 1), (2, 2, 1, 0), (3, 2, 1, 0), (4, 2, 0, 1), (4, 3, 1, 0), (5, 3, 0, 1)) v(step, phase, r, w), (SELECT count(*) AS n FROM orders) GROUP BY step, phase")


@query("cost_extrapolation", "SELECT o_orderkey, n, CAST(runs AS BIGINT) AS runs, CAST(merges AS BIGINT) AS merges, round(h * (14 + 4 * (merges - 1)), 4) AS staged_h, round(h * (6 + 4 * (merges - 1)), 4) AS fused_h, round(h * 8, 4) AS saved_h FROM (SELECT *, CASE WHEN runs <= 1 THEN 0 WHEN runs <= fan THEN 1 WHEN runs <= fan * fan THEN 2 WHEN runs <= fan * fan * fan THEN 3 WHEN runs <= fan * fan * fan * fan THEN 4 END AS merges FROM (SELECT o_orderkey, n, m / 1e3::DOUBLE AS fan, ceil(n / m) AS runs, n / 1e8::DOUBLE / 3600 AS h FROM (SELECT o_orderkey, o_totalprice * 1e9::DOUBLE AS n, (1 + o_custkey % 50) * 1e6::DOUBLE AS m FROM orders)))")
def cost_extrapolation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each order stands for a regridding of its price in 10^9 items, its customer for 1 to 50 times 10^6 items of memory; blocks of 1000 items of a byte, 100 MB a second."""
    jobs = table(spark, sf_dir, "orders").select("o_orderkey", (F.col("o_totalprice") * 1e9).alias("n"), ((1 + F.col("o_custkey") % 50) * 1e6).alias("m"), F.lit(1e3).alias("b"), F.lit(1).alias("item"), F.lit(1e8).alias("speed"))
    return cost.extrapolate(jobs, "o_orderkey")


@query("cost_scan_sort", "SELECT n, b, CAST((n + b - 1) // b AS BIGINT) AS scan, round(greatest(1, ln(n / b::DOUBLE) / ln(m / b::DOUBLE)) * n / b::DOUBLE, 3) AS sort FROM (SELECT count(*) AS n, 10::BIGINT AS b, 1000::BIGINT AS m FROM orders)")
def cost_scan_sort(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = table(spark, sf_dir, "orders").count()
    df = spark.createDataFrame([(n, 10, 1000)], "n long, b long, m long")
    return df.select("n", "b", cost.scan_ios_col(F.col("n"), F.col("b")).alias("scan"), F.lit(round(cost.sort_ios(n, 1000, 10), 3)).alias("sort"))


# Phases and orders


def part_pipeline(parts: list[tuple]) -> FlowGraph:
    """Parts (key, size) as the components of a pipeline, one after another: those whose size divides by 4 block, and by 8 are pulled."""
    g, before = FlowGraph(), None
    for key, size in parts:
        if size % 4 == 0:
            g.blocking(f"{key}S")
        else:
            g.node(f"{key}")
        into, out = (f"{key}Si", f"{key}So") if size % 4 == 0 else (f"{key}", f"{key}")
        if before:
            g.edges.append(Edge(before[0], into, PULL if before[1] else PUSH))
        before = out, size % 8 == 0
    return g


def part_pipelines(spark: SparkSession, sf_dir: str, each: Callable[[FlowGraph], list[tuple]], schema: str) -> DataFrame:
    """Every ten parts are a pipeline; the rows that `each` finds for its flow graph, in the tasks."""
    return by_blocks(table(spark, sf_dir, "part"), "p_partkey", 10, ["p_size"], lambda block, parts: [(block, *r) for r in each(part_pipeline(parts))], f"graph long, {schema}")


#: Nodes of part_pipeline: place in the graph, phase, and whether the edge out of a phase's first node is a pull edge.
_NODES = """
WITH c AS (SELECT p_partkey AS key, p_partkey // 10 AS graph, p_size % 4 = 0 AS blocks, p_size % 8 = 0 AS pulled, CAST(count(*) FILTER (WHERE p_size % 4 = 0) OVER (PARTITION BY p_partkey // 10 ORDER BY p_partkey) AS INTEGER) AS k FROM part),
n AS (SELECT graph, 2 * key AS pos, CASE WHEN blocks THEN key || 'Si' ELSE CAST(key AS VARCHAR) END AS node, CASE WHEN blocks THEN k ELSE k + 1 END AS phase, false AS pulled FROM c UNION ALL SELECT graph, 2 * key + 1, key || 'So', k + 1, pulled FROM c WHERE blocks)
"""


@query("phases_example", _NODES + "SELECT graph, node, phase FROM n")
def phases_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    return part_pipelines(spark, sf_dir, lambda g: list(phases.identify(g).items()), "node string, phase int")


@query("orders_example", _NODES + """, p AS (SELECT *, pulled AND count(*) OVER (PARTITION BY graph, phase) > 1 AS first FROM n),
o AS (SELECT graph, phase, string_agg(node, ',' ORDER BY pos) AS d, string_agg(node, ',' ORDER BY first DESC, pos DESC) AS o, arg_min(node, pos) FILTER (WHERE NOT first) AS i, string_agg(node, ',' ORDER BY first, pos) AS c FROM p GROUP BY graph, phase)
SELECT graph, phase, unnest(['describe', 'open', 'drive', 'close']) AS hook, unnest([d, o, i, c]) AS nodes FROM o""")
def orders_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    hooks = {"describe": order.describe, "open": order.open, "drive": order.initiators, "close": order.close}
    return part_pipelines(spark, sf_dir, lambda g: [(k, h, ",".join(f(g, names))) for k, names in enumerate(phases.order(g), 1) for h, f in hooks.items()], "phase int, hook string, nodes string")


@query("metadata_reach_example", _NODES + "SELECT a.graph, a.node AS from_node, b.node AS to_node FROM n a JOIN n b ON a.graph = b.graph AND a.pos < b.pos")
def metadata_reach(spark: SparkSession, sf_dir: str) -> DataFrame:
    return part_pipelines(spark, sf_dir, lambda g: sorted(g.reach()), "from_node string, to_node string")


def bulk_graph(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    """nodes (graph, node) and edges (graph, src, dst, kind) of the flow graphs that a table stands for."""
    df = table(spark, sf_dir, name)
    if name == "conversations":
        rows = df.select(F.col("conv_id").alias("graph"), F.col("turn").alias("node"), "role")
        before = rows.select("graph", (F.col("node") + 1).alias("node"), F.col("node").alias("src"))
        edges = rows.join(before, ["graph", "node"]).select("graph", "src", F.col("node").alias("dst"), F.when(F.col("role") == "user", "blocking").otherwise("push").alias("kind"))
    elif name == "orders":
        rows = df.select(F.lit(0).cast("long").alias("graph"), F.col("o_orderkey").alias("node"), F.col("o_orderstatus").alias("status"))
        child = rows.where("node > 0").select("graph", F.col("node").alias("dst"), div(F.col("node") - 1, 2).alias("node"))
        edges = child.join(rows, ["graph", "node"]).select("graph", F.col("node").alias("src"), "dst", F.when(F.col("status") == "P", "blocking").otherwise("push").alias("kind"))
    else:
        from pyspark.sql import Window

        w = Window.partitionBy("graph").orderBy("ts", "node")
        rows = df.select(F.col("user_id").alias("graph"), F.col("event_id").alias("node"), "ts", "event_type").withColumn("dst", F.lead("node").over(w))
        edges = rows.where("dst is not null").select("graph", F.col("node").alias("src"), "dst", F.when(F.col("event_type") == "purchase", "blocking").otherwise("push").alias("kind"))
    return rows.select("graph", "node"), edges


def bulk_phases(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return phases.identify_df(*(materialise(x, "graph") for x in bulk_graph(spark, sf_dir, name)))


def bulk_levels(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    nodes, edges = (materialise(x, "graph") for x in bulk_graph(spark, sf_dir, name))
    return phases.order_df(phases.identify_df(nodes, edges), edges)


_CONV = "WITH c AS (SELECT conv_id AS graph, turn AS node, count(*) FILTER (WHERE role = 'user' AND turn > 0) OVER (PARTITION BY conv_id ORDER BY turn) AS k FROM conversations)"
_EVENTS = "WITH p AS (SELECT user_id AS graph, event_id AS node, coalesce(sum(CASE WHEN event_type = 'purchase' THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS k FROM events)"
_TREE = "WITH RECURSIVE t(node, phase, level) AS (SELECT o_orderkey, o_orderkey, 0::BIGINT FROM orders WHERE o_orderkey = 0 UNION ALL SELECT c.o_orderkey, CASE WHEN p.o_orderstatus = 'P' THEN c.o_orderkey ELSE t.phase END, CASE WHEN p.o_orderstatus = 'P' THEN t.level + 1 ELSE t.level END FROM t JOIN orders p ON p.o_orderkey = t.node JOIN orders c ON c.o_orderkey IN (2 * t.node + 1, 2 * t.node + 2))"
add("phases_conversations", partial(bulk_phases, name="conversations"), _CONV + " SELECT graph, node, min(node) OVER (PARTITION BY graph, k) AS phase FROM c")
add("phases_events", partial(bulk_phases, name="events"), _EVENTS + " SELECT graph, node, min(node) OVER (PARTITION BY graph, k) AS phase FROM p")
add("phases_orders_tree", partial(bulk_phases, name="orders"), _TREE + " SELECT 0::BIGINT AS graph, node, phase FROM t")
add("phase_levels_conversations", partial(bulk_levels, name="conversations"), _CONV + " SELECT graph, min(node) AS phase, CAST(k - min(k) OVER (PARTITION BY graph) AS BIGINT) AS level FROM c GROUP BY graph, k")
add("phase_levels_events", partial(bulk_levels, name="events"), _EVENTS + " SELECT graph, min(node) AS phase, CAST(k AS BIGINT) AS level FROM p GROUP BY graph, k")
add("phase_levels_orders_tree", partial(bulk_levels, name="orders"), _TREE + " SELECT DISTINCT 0::BIGINT AS graph, phase, level FROM t")


# Memory


ASKS = {"part": ("p_brand", "p_partkey", "p_size"), "supplier": ("CAST(s_nationkey AS VARCHAR)", "s_suppkey", "1 + s_suppkey % 50")}


def memory_asks(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    phase, node, lo = (F.expr(x.replace("VARCHAR", "STRING")) for x in ASKS[name])
    lo, node = lo.cast("long"), node.cast("long")
    asks = table(spark, sf_dir, name).select(phase.alias("phase"), node.alias("node"), lo.alias("lo"), F.when(node % 10 != 0, 4 * lo).alias("hi"), (1 + node % 7).alias("prio"))
    return asks, asks.groupBy("phase").agg((2 * F.sum("lo")).alias("available"))


def memory_sql(name: str, select: str) -> str:
    phase, node, lo = ASKS[name]
    return f"""
WITH asks AS (SELECT phase, node, lo, CASE WHEN node % 10 != 0 THEN 4 * lo END AS hi, 1 + node % 7 AS prio FROM (SELECT {phase} AS phase, CAST({node} AS BIGINT) AS node, CAST({lo} AS BIGINT) AS lo FROM {name})),
budgets AS (SELECT phase, CAST(2 * sum(lo) AS DOUBLE) AS available FROM asks GROUP BY phase),
points AS (SELECT phase, lo / prio::DOUBLE AS lam FROM asks UNION SELECT phase, hi / prio::DOUBLE FROM asks WHERE hi IS NOT NULL UNION SELECT phase, 1e9 FROM asks),
totals AS (SELECT p.phase, p.lam, sum(greatest(a.lo, least(coalesce(a.hi, 'infinity'::DOUBLE), p.lam * a.prio))) AS total FROM points p JOIN asks a USING (phase) GROUP BY ALL),
low AS (SELECT t.phase, max(t.lam) AS l0, max(t.total) AS t0 FROM totals t JOIN budgets b USING (phase) WHERE t.total <= b.available + 1e-9 GROUP BY ALL),
high AS (SELECT t.phase, min(t.lam) AS l1, min(t.total) AS t1 FROM totals t JOIN budgets b USING (phase) WHERE t.total > b.available + 1e-9 GROUP BY ALL),
solved AS (SELECT phase, l0 + (available - t0) / (t1 - t0) * (l1 - l0) AS lam FROM low JOIN high USING (phase) JOIN budgets USING (phase)),
full_ AS (SELECT phase FROM asks JOIN budgets USING (phase) GROUP BY phase, available HAVING count(hi) = count(*) AND sum(hi) <= available)
{select}
"""


def memory_case(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    asks, budgets = memory_asks(spark, sf_dir, name)
    return memory.assign_df(asks, budgets).select("phase", "node", F.round("assigned", 5).alias("assigned"))


_ASSIGNED = "SELECT a.phase, a.node, round(CASE WHEN f.phase IS NOT NULL THEN CAST(a.hi AS DOUBLE) ELSE greatest(CAST(a.lo AS DOUBLE), least(coalesce(CAST(a.hi AS DOUBLE), 'infinity'::DOUBLE), s.lam * a.prio)) END, 5) AS assigned FROM asks a LEFT JOIN solved s USING (phase) LEFT JOIN full_ f USING (phase)"
for _t in ASKS:
    add(f"memory_assign_{_t}", partial(memory_case, name=_t), memory_sql(_t, _ASSIGNED))


#: Budgets of the worked example, in twentieths of the least that a phase asks for.
LEVELS = (20, 23, 36, 60)

_FIG = """
WITH asks AS (SELECT p_partkey // 4 * 100 + level AS phase, p_partkey // 4 AS block, level, p_partkey AS node, CAST(p_size AS BIGINT) AS lo, CASE WHEN p_partkey % 10 != 0 THEN CAST(4 * p_size AS BIGINT) END AS hi, 1 + p_partkey % 7 AS prio FROM part, (VALUES (20), (23), (36), (60)) l(level)),
budgets AS (SELECT phase, sum(lo) * any_value(level) / 20.0::DOUBLE AS available FROM asks GROUP BY phase),
points AS (SELECT phase, lo / prio::DOUBLE AS lam FROM asks UNION SELECT phase, hi / prio::DOUBLE FROM asks WHERE hi IS NOT NULL UNION SELECT phase, 1e6 FROM asks),
totals AS (SELECT p.phase, p.lam, sum(greatest(a.lo, least(coalesce(a.hi, 'infinity'::DOUBLE), p.lam * a.prio))) AS total FROM points p JOIN asks a USING (phase) GROUP BY ALL),
low AS (SELECT t.phase, max(t.lam) AS l0, max(t.total) AS t0 FROM totals t JOIN budgets b USING (phase) WHERE t.total <= b.available + 1e-9 GROUP BY ALL),
high AS (SELECT t.phase, min(t.lam) AS l1, min(t.total) AS t1 FROM totals t JOIN budgets b USING (phase) WHERE t.total > b.available + 1e-9 GROUP BY ALL),
solved AS (SELECT phase, l0 + (available - t0) / (t1 - t0) * (l1 - l0) AS lam FROM low JOIN high USING (phase) JOIN budgets USING (phase)),
full_ AS (SELECT phase FROM asks JOIN budgets USING (phase) GROUP BY phase, available HAVING count(hi) = count(*) AND sum(hi) <= available)
SELECT a.block, b.available AS budget, chr(CAST(65 + a.node % 4 AS INTEGER)) AS node, round(CASE WHEN f.phase IS NOT NULL THEN CAST(a.hi AS DOUBLE) ELSE greatest(CAST(a.lo AS DOUBLE), least(coalesce(CAST(a.hi AS DOUBLE), 'infinity'::DOUBLE), s.lam * a.prio)) END, 9) AS assigned FROM asks a JOIN budgets b USING (phase) LEFT JOIN solved s USING (phase) LEFT JOIN full_ f USING (phase)
"""


@query("memory_fig", _FIG)
def memory_fig(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The worked example's four components and budgets on part: four parts are a phase, assigned memory exactly, in the tasks."""

    def assigned(block: int, parts: list[tuple]) -> list[tuple]:
        asks = {"ABCD"[key % 4]: memory.MemoryAsk(size, 4 * size if key % 10 else math.inf, 1 + key % 7) for key, size in parts}
        budgets = [sum(a.lo for a in asks.values()) * level / 20 for level in LEVELS]
        return [(block, b, n, round(float(v), 9)) for b in budgets for n, v in memory.assign(asks, b)[1].items()]

    return by_blocks(table(spark, sf_dir, "part"), "p_partkey", 4, ["p_size"], assigned, "block long, budget double, node string, assigned double")


@query("memory_curve_part", memory_sql("part", "SELECT phase, l.lam, round(sum(greatest(lo, least(coalesce(hi, 'infinity'::DOUBLE), l.lam * prio))), 5) AS total FROM asks, (VALUES (0.5::DOUBLE), (2.0), (8.0), (32.0)) l(lam) GROUP BY ALL"))
def memory_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    asks, _ = memory_asks(spark, sf_dir, "part")
    return memory.curve_df(asks, [0.5, 2.0, 8.0, 32.0]).withColumn("total", F.round("total", 5))


# Progress


def run_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stands for a log of runs: a user's day is a run, an event type a phase, the value its seconds."""
    e = table(spark, sf_dir, "events").select(F.col("user_id").cast("string").alias("pipeline_id"), F.date_format("ts", "yyyy-MM-dd").alias("run_id"), F.col("event_type").alias("phase"), F.col("value").cast("decimal(18,2)").alias("seconds"), "event_id", "ts")
    return e


_LOG = "WITH e AS (SELECT CAST(user_id AS VARCHAR) AS pipeline_id, strftime(ts, '%Y-%m-%d') AS run_id, event_type AS phase, CAST(value AS DECIMAL(18,2)) AS seconds, event_id, ts FROM events), runs AS (SELECT pipeline_id, run_id, count(*) AS size FROM e GROUP BY ALL), best AS (SELECT pipeline_id, run_id FROM runs QUALIFY row_number() OVER (PARTITION BY pipeline_id ORDER BY size DESC, run_id DESC) = 1), big AS (SELECT e.* FROM e JOIN best USING (pipeline_id, run_id)), shares AS (SELECT pipeline_id, phase, CAST(sum(seconds) AS DOUBLE) / sum(CAST(sum(seconds) AS DOUBLE)) OVER (PARTITION BY pipeline_id) AS share FROM big GROUP BY pipeline_id, phase)"


def log_shares(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = run_log(spark, sf_dir)
    per = e.groupBy("pipeline_id", "run_id", "phase").agg(F.sum("seconds").cast("double").alias("seconds"), F.count("*").alias("steps"))
    sizes = per.groupBy("pipeline_id", "run_id").agg(F.sum("steps").alias("size"))
    return progress.shares_df(per.join(sizes, ["pipeline_id", "run_id"]))


@query("progress_shares_events", _LOG + " SELECT pipeline_id, phase, round(share, 6) AS share FROM shares")
def progress_shares(spark: SparkSession, sf_dir: str) -> DataFrame:
    return log_shares(spark, sf_dir).withColumn("share", F.round("share", 6))


def _curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each run's events in time order; an event moves the bar by its phase's share, dealt evenly over the run's events of the phase."""
    from pyspark.sql import Window

    # not fillna, which would make 0 of the NaN of a largest run without time, too
    e = run_log(spark, sf_dir).join(log_shares(spark, sf_dir), ["pipeline_id", "phase"], "left").withColumn("share", F.coalesce("share", F.lit(0.0)))
    w = Window.partitionBy("pipeline_id", "run_id", "phase")
    e = e.withColumn("part", F.col("share") / F.count("*").over(w))
    return progress.curve_df(e, ["pipeline_id", "run_id"], ["ts", "event_id"], F.col("seconds").cast("double"), F.col("part"))


_CURVE = _LOG + ", parts AS (SELECT e.*, coalesce(s.share, 0) / count(*) OVER (PARTITION BY e.pipeline_id, e.run_id, e.phase) AS part FROM e LEFT JOIN shares s ON e.pipeline_id = s.pipeline_id AND e.phase = s.phase), curve AS (SELECT pipeline_id, run_id, event_id, sum(CAST(seconds AS DOUBLE)) OVER w / sum(CAST(seconds AS DOUBLE)) OVER (PARTITION BY pipeline_id, run_id) AS t, sum(part) OVER w AS p FROM parts WINDOW w AS (PARTITION BY pipeline_id, run_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING))"


@query("progress_curve_events", _CURVE + " SELECT pipeline_id, run_id, event_id, round(p, 6) AS p FROM curve")
def progress_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _curve(spark, sf_dir).select("pipeline_id", "run_id", "event_id", F.round("p", 6).alias("p"))


@query("progress_pace_events", _CURVE + " SELECT pipeline_id, run_id, round(max(abs(p - t)), 6) AS err FROM curve GROUP BY ALL")
def progress_pace(spark: SparkSession, sf_dir: str) -> DataFrame:
    return progress.pace_error(_curve(spark, sf_dir), ["pipeline_id", "run_id"]).withColumn("err", F.round("err", 6))


@query("progress_pace_equal_events", _LOG + ", parts AS (SELECT *, 0.2::DOUBLE / count(*) OVER (PARTITION BY pipeline_id, run_id, phase) AS part FROM e), curve AS (SELECT pipeline_id, run_id, sum(CAST(seconds AS DOUBLE)) OVER w / sum(CAST(seconds AS DOUBLE)) OVER (PARTITION BY pipeline_id, run_id) AS t, sum(part) OVER w AS p FROM parts WINDOW w AS (PARTITION BY pipeline_id, run_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)) SELECT pipeline_id, run_id, round(max(abs(p - t)), 6) AS err FROM curve GROUP BY ALL")
def progress_pace_equal(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ablation: every phase the same share, whatever it took before."""
    from pyspark.sql import Window

    w = Window.partitionBy("pipeline_id", "run_id", "phase")
    e = run_log(spark, sf_dir).withColumn("part", F.lit(progress.equal_shares(5)[0]) / F.count("*").over(w))
    curve = progress.curve_df(e, ["pipeline_id", "run_id"], ["ts", "event_id"], F.col("seconds").cast("double"), F.col("part"))
    return progress.pace_error(curve, ["pipeline_id", "run_id"]).withColumn("err", F.round("err", 6))


# Sorting, blocking kinds, parallel copies, chains

LINE_KEY = ["l_shipdate", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus"]
LINE_OUT = ["l_orderkey", "l_linenumber", "l_partkey"]


def arrivals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem in an order of arrival that isn't the sort order, with its positions."""
    key = ["l_orderkey", *[c for c in LINE_KEY if c != "l_orderkey"]]
    return with_positions(table(spark, sf_dir, "lineitem"), *key)


_ORDER = ", ".join(LINE_KEY)
_ARRIVE = f"WITH a AS (SELECT *, row_number() OVER (ORDER BY l_orderkey, {', '.join(c for c in LINE_KEY if c != 'l_orderkey')}) - 1 AS pos FROM lineitem)"


def runs_sql(m: int) -> str:
    return f"{_ARRIVE} SELECT CAST(pos // {m} AS BIGINT) AS run_id, CAST(row_number() OVER (PARTITION BY pos // {m} ORDER BY {_ORDER}) - 1 AS BIGINT) AS pos_in_run, l_orderkey, l_linenumber, l_partkey FROM a"


@query("runs_lineitem", runs_sql(1000))
def runs_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    runs = extsort.in_runs(extsort.form_runs(arrivals(spark, sf_dir), 1000), LINE_KEY)
    return extsort.numbered(runs, LINE_KEY).select("run_id", "pos_in_run", *LINE_OUT)


@query("merge_pass1_lineitem", runs_sql(4000))
def merge_pass1(spark: SparkSession, sf_dir: str) -> DataFrame:
    runs = extsort.merge_runs(extsort.form_runs(arrivals(spark, sf_dir), 1000), 4)
    return extsort.numbered(extsort.in_runs(runs, LINE_KEY), LINE_KEY).select("run_id", "pos_in_run", *LINE_OUT)


@query("external_sort_lineitem", runs_sql(10**12))
def external_sort_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All passes; the one run that is left gets its positions by range, not in a window over everything."""
    out = extsort.external_sort(arrivals(spark, sf_dir), LINE_KEY, 1000, 4, stored=False)
    return numbered(out.drop("pos")).select("run_id", F.col("pos").alias("pos_in_run"), *LINE_OUT)


@query("run_stats_lineitem", f"{_ARRIVE} SELECT CAST(pos // 1000 AS BIGINT) AS run_id, min(l_partkey) AS low, max(l_partkey) AS high, count(*) AS items FROM a GROUP BY 1")
def run_stats_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extsort.run_stats(extsort.form_runs(arrivals(spark, sf_dir), 1000), "l_partkey")


@query("global_position_lineitem", f"SELECT CAST(row_number() OVER (ORDER BY {_ORDER}) - 1 AS BIGINT) AS pos, l_orderkey, l_linenumber, l_partkey FROM lineitem")
def global_position(spark: SparkSession, sf_dir: str) -> DataFrame:
    return with_positions(table(spark, sf_dir, "lineitem"), *LINE_KEY).select("pos", *LINE_OUT)


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select(F.col("event_id").alias("pos"), "user_id", "event_type")


def blocking_case(spark: SparkSession, sf_dir: str, kind: str, passive: bool) -> DataFrame:
    """A stream through a blocking component; the passive one's consumer pulls it beside the stream that it came from."""
    if kind == "sort":
        s, sort = table(spark, sf_dir, "lineitem"), pipeline.Sort(*LINE_KEY, name="S")
        if not passive:
            p = pipeline.Pipeline(pipeline.Source(s, "read") | sort | pipeline.Map(numbered, "number"))
        else:
            sort = sort.pulled()
            beside = pipeline.Source(spark.range(s.count()).withColumnRenamed("id", "pos"), "count")
            # a pulled sort gives its list; the consumer that reads it beside the numbers brings the order
            scan = pipeline.Join(lambda numbers, pulled: zip_streams(numbers, with_positions(pulled, *LINE_KEY)), "scan")
            p = pipeline.Pipeline(pipeline.Source(s, "read") | sort.input, beside | scan, extra=[(sort.output, scan)])
        return next(iter(p.run(spark)[0].values())).select("pos", *LINE_OUT)
    s = events_stream(spark, sf_dir)
    n = s.count()
    made = pipeline.Delay(name="X") if kind == "delay" else pipeline.Reverse(name="X")
    if not passive:
        p = pipeline.Pipeline(pipeline.Source(s, "read") | made | pipeline.Map(lambda d: d, "give"))
    else:
        made = made.pulled()
        beside = pipeline.Source(spark.range(n).withColumnRenamed("id", "pos"), "count")
        scan = pipeline.Join(zip_streams, "scan")
        p = pipeline.Pipeline(pipeline.Source(s, "read") | made.input, beside | scan, extra=[(made.output, scan)])
    p.publish("items", n)
    return next(iter(p.run(spark)[0].values())).select("pos", "user_id", "event_type")


for _v in ("active", "passive"):
    add(f"delay_{_v}_events", partial(blocking_case, kind="delay", passive=_v == "passive"), "SELECT event_id AS pos, user_id, event_type FROM events")
    add(f"reverse_{_v}_events", partial(blocking_case, kind="reverse", passive=_v == "passive"), "SELECT (SELECT count(*) FROM events) - 1 - event_id AS pos, user_id, event_type FROM events")
    add(f"sort_{_v}_lineitem", partial(blocking_case, kind="sort", passive=_v == "passive"), f"SELECT CAST(row_number() OVER (ORDER BY {_ORDER}) - 1 AS BIGINT) AS pos, l_orderkey, l_linenumber, l_partkey FROM lineitem")


@query("delay_zip_events", "SELECT pos, a.event_id, b.event_id AS sorted_event_id FROM (SELECT event_id, event_id AS pos FROM events) a JOIN (SELECT event_id, CAST(row_number() OVER (ORDER BY user_id, ts) - 1 AS BIGINT) AS pos FROM events) b USING (pos)")
def delay_zip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """u goes to a sorter and, over a delay, to the consumer that pulls the sorter: event i beside the i-th by user and time."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts")
    kept = materialise(e)
    return zip_streams(kept.select("event_id", F.col("event_id").alias("pos")), with_positions(kept, "user_id", "ts").select("pos", F.col("event_id").alias("sorted_event_id"))).select("pos", "event_id", "sorted_event_id")


@query("parallel_assignment_events", "SELECT (event_id // 2048) % 4 AS worker, count(*) AS items, CAST(count(DISTINCT event_id // 2048) AS BIGINT) AS batches FROM events GROUP BY 1")
def parallel_assignment(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").select(F.col("event_id").alias("pos"))
    return e.groupBy(worker_of(F.col("pos"), workers=4).alias("worker")).agg(F.count("*").alias("items"), F.count_distinct(div(F.col("pos"), 2048)).alias("batches"))


@query("parallel_mapping_orders", "SELECT CAST(o_orderkey AS BIGINT) AS pos, (o_orderkey % (SELECT count(*) // 100 FROM orders)) * 100 + o_orderkey // (SELECT count(*) // 100 FROM orders) AS src FROM orders")
def parallel_mapping(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The regridding's cell mapper run by four workers, each dealt every fourth batch of 2048 items."""
    _, shape = table_grid(spark, sf_dir, "orders", "o_orderkey", "o_totalprice", width=100)
    f = maps.transpose(shape)
    cells = pipeline.Source(spark.range(f.target.n).withColumnRenamed("id", "pos"), "cells")
    mapper = pipeline.parallel(pipeline.Map(lambda d: d.withColumn("src", f.of(F.col("pos")).cast("long")), "map"), workers=4)
    return next(iter(pipeline.Pipeline(cells | mapper).run(spark)[0].values())).select("pos", "src")


@query("progress_three_scales_part", "SELECT CAST(scale AS INTEGER) AS scale, CAST(3 AS INTEGER) AS phases, CAST(scale > 1 AS BOOLEAN) AS has_history, true AS largest_gives_shares FROM (VALUES (1), (2), (3)) v(scale)")
def progress_three_scales(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The regridding of part's grid, then of two larger grids, against one store: each run's bar uses the shares of the largest run before it."""
    a, shape = table_grid(spark, sf_dir, "part", "p_partkey", "p_retailprice", width=50)
    store = progress.ProgressStore(spark, fresh_path(spark, "times"))
    rows = []
    for scale in (1, 2, 3):
        grown = GridShape(shape.width, shape.height * scale)
        cells = a
        for i in range(1, scale):
            cells = cells.unionByName(a.withColumn("cell", F.col("cell") + i * shape.n))
        before = store.shares("three scales")
        report = pipeline.regrid(cells, maps.transpose(grown)).run(spark, mode="by_phase", size=grown.n, store=store, identity="three scales", action=lambda d: d.write.format("noop").mode("overwrite").save())[1]
        after, whole = store.shares("three scales"), sum(report.seconds)
        rows.append((scale, len(report.phases), before is not None, all(abs(x - y / whole) < 1e-9 for x, y in zip(after, report.seconds, strict=True))))
    return spark.createDataFrame(rows, "scale int, phases int, has_history boolean, largest_gives_shares boolean")


def chain_case(spark: SparkSession, sf_dir: str, k: int, mode: str) -> DataFrame:
    """k small components one after another over lineitem."""
    s = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.col("l_suppkey").alias("value"))
    return next(iter(pipeline.Pipeline(chain_of(s, k)).run(spark, mode=mode)[0].values()))


def chain_of(s: DataFrame, k: int) -> pipeline.Chain:
    chain = pipeline.Source(s, "read")
    for i in range(k):
        chain = chain | pipeline.Map(lambda d, i=i: d.withColumn("value", (F.col("value") * 3 + i) % 1000003), f"map{i}")
    return chain


def chain_sql(k: int) -> str:
    value = "l_suppkey"
    for i in range(k):
        value = f"(({value}) * 3 + {i}) % 1000003"
    return f"SELECT l_orderkey, l_linenumber, l_partkey, {value} AS value FROM lineitem"


for _k in (1, 2, 4, 8, 16):
    add(f"chain_k{_k}_lineitem", partial(chain_case, k=_k, mode="fused"), chain_sql(_k))
    add(f"chain_k{_k}_materialised_lineitem", partial(chain_case, k=_k, mode="materialised"), chain_sql(_k))


@query("chain_traffic_lineitem", "SELECT CAST(k AS INTEGER) AS k, CAST(2 * k * n AS BIGINT) AS staged, CAST(2 * n AS BIGINT) AS fused, round(1 - 1.0::DOUBLE / k, 6) AS saved FROM (VALUES (1), (2), (4), (8), (16)) v(k), (SELECT count(*) AS n FROM lineitem)")
def chain_traffic(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Records read and written by the tasks of chains that run, every component's list written or only the last one's."""
    s = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.col("l_suppkey").alias("value"))

    def moved(k: int, mode: str) -> int:
        # materialised, the last list is the output; fused, the output is what is written
        def job() -> None:
            materialise(next(iter(pipeline.Pipeline(chain_of(s, k)).run(spark)[0].values())), "output")

        if mode == "fused":
            groups = [metrics.run_in_group(spark, job)]
        else:
            groups = pipeline.Pipeline(chain_of(s, k)).run(spark, mode=mode)[1].groups
        return sum(int(metrics.stage_traffic(spark, g).agg(F.sum(F.col("in_records") + F.col("out_records"))).first()[0] or 0) for g in groups)

    rows = []
    for k in (1, 2, 4, 8, 16):
        staged, fused = moved(k, "materialised"), moved(k, "fused")
        rows.append((k, staged, fused, round(1 - fused / staged, 6) if staged else 0.0))
    return spark.createDataFrame(rows, "k int, staged long, fused long, saved double")


# The large pipeline: over forty components, five tables and a text branch


def big_pipeline(spark: SparkSession, sf_dir: str) -> pipeline.Pipeline:
    """customer, orders, lineitem, part and supplier meet in sorted co-scans, six small components between each; texts by their numbers."""
    P = pipeline
    t = partial(table, spark, sf_dir)

    def maps_(name: str, first, key: str) -> P.Chain:
        """Small components that check and tidy a stream by its key."""
        small = (
            lambda d: d.where(F.col(key).isNotNull()),
            lambda d: d.withColumn(key, F.col(key).cast("long")),
            lambda d: d.withColumn("valid", F.col(key) >= 0),
            lambda d: d.where("valid"),
            lambda d: d.drop("valid"),
            lambda d: d.select(key, *(c for c in d.columns if c != key)),
        )
        chain = first
        for i, f in enumerate(small):
            chain = chain | P.Map(f, f"{name}{i}")
        return chain

    def scan(name: str, key: str, how: str = "inner") -> P.Join:
        return P.Join(lambda a, b: a.join(b.hint("merge"), key, how), name)

    c = P.Sort("c_custkey", name="Sc").pulled()
    s = P.Sort("l_suppkey", name="Ss").pulled()
    p = P.Sort("l_partkey", name="Sp").pulled()
    o = P.Sort("l_orderkey", name="So").pulled()
    d = P.Sort("nation", name="Sd").pulled()
    cust = maps_("cust", P.Source(t("customer").select(F.col("c_custkey").alias("c_custkey"), F.col("c_nationkey").alias("nation")), "customer"), "c_custkey") | c.input
    ords = P.Source(t("orders").select(F.col("o_custkey").alias("c_custkey"), F.col("o_orderkey").alias("l_orderkey"), F.year("o_orderdate").alias("year")), "orders") | (j1 := scan("co1", "c_custkey"))
    ords = maps_("ord", ords, "l_orderkey") | o.input
    supp = maps_("supp", P.Source(t("supplier").select(F.col("s_suppkey").alias("l_suppkey")), "supplier"), "l_suppkey") | s.input
    part = maps_("part", P.Source(t("part").where("p_size > 10").select(F.col("p_partkey").alias("l_partkey")), "part"), "l_partkey") | p.input
    docs = P.Source(t("documents").select((F.col("doc_id") % 25).cast("int").alias("nation"), F.size(F.split("text", " ")).cast("long").alias("tokens")), "documents")
    text = maps_("text", docs, "nation") | P.Map(lambda x: x.groupBy("nation").agg(F.sum("tokens").alias("doc_tokens")), "count") | d.input
    money = (F.col("l_extendedprice").cast("decimal(18,2)") * (F.lit(1).cast("decimal(3,0)") - F.col("l_discount").cast("decimal(4,2)"))).cast("decimal(18,4)")
    line = P.Source(t("lineitem").select("l_orderkey", "l_partkey", "l_suppkey", money.alias("revenue")), "lineitem") | (j2 := scan("co2", "l_orderkey")) | P.Sort("l_partkey", name="S5") | (j3 := scan("co3", "l_partkey"))
    line = line | P.Sort("l_suppkey", name="S6") | (j4 := scan("co4", "l_suppkey")) | P.Map(lambda x: x.groupBy("nation", "year").agg(F.sum("revenue").cast("decimal(18,4)").alias("revenue")), "sum")
    line = line | P.Sort("nation", name="S7") | (j5 := scan("co5", "nation", "left")) | P.Map(lambda x: x.select("nation", F.col("year").cast("int").alias("year"), F.col("revenue").cast("double").alias("revenue"), "doc_tokens"), "give")
    return P.Pipeline(cust, ords, supp, part, text, line, extra=[(c.output, j1), (o.output, j2), (p.output, j3), (s.output, j4), (d.output, j5)])


@query("big_pipeline_result", "WITH docs AS (SELECT doc_id % 25 AS nation, CAST(sum(len(string_split(text, ' '))) AS BIGINT) AS doc_tokens FROM documents GROUP BY 1), r AS (SELECT c_nationkey AS nation, CAST(year(o_orderdate) AS INTEGER) AS year, CAST(sum(CAST(CAST(l_extendedprice AS DECIMAL(18,2)) * (1 - CAST(l_discount AS DECIMAL(4,2))) AS DECIMAL(18,4))) AS DOUBLE) AS revenue FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN part ON p_partkey = l_partkey AND p_size > 10 JOIN supplier ON s_suppkey = l_suppkey GROUP BY 1, 2) SELECT r.nation, r.year, r.revenue, d.doc_tokens FROM r LEFT JOIN docs d ON d.nation = r.nation")
def big_pipeline_result(spark: SparkSession, sf_dir: str) -> DataFrame:
    return next(iter(big_pipeline(spark, sf_dir).run(spark)[0].values()))


def _tidied(n: str, rows: str, key: str) -> str:
    """Items before the six small components of a chain, after the first, and after the fourth."""
    return f"{n} AS (SELECT count(*) AS a, count({key}) AS b, count(*) FILTER (WHERE {key} >= 0) AS c FROM {rows})"


_TRAFFIC = f"""
WITH j1 AS (SELECT o_orderkey, c_nationkey, year(o_orderdate) AS year FROM orders JOIN (SELECT * FROM customer WHERE c_custkey >= 0) ON o_custkey = c_custkey),
j2 AS (SELECT l_partkey, l_suppkey, c_nationkey, year FROM lineitem JOIN (SELECT * FROM j1 WHERE o_orderkey >= 0) ON l_orderkey = o_orderkey),
j3 AS (SELECT j2.* FROM j2 JOIN (SELECT * FROM part WHERE p_size > 10 AND p_partkey >= 0) ON l_partkey = p_partkey),
j4 AS (SELECT j3.* FROM j3 JOIN (SELECT * FROM supplier WHERE s_suppkey >= 0) ON l_suppkey = s_suppkey),
r AS (SELECT DISTINCT c_nationkey, year FROM j4),
{_tidied("c", "customer", "c_custkey")}, {_tidied("o", "j1", "o_orderkey")}, {_tidied("s", "supplier", "s_suppkey")}, {_tidied("p", "(SELECT * FROM part WHERE p_size > 10)", "p_partkey")}, {_tidied("d", "(SELECT doc_id % 25 AS nation FROM documents)", "nation")},
k AS (SELECT (SELECT count(*) FROM orders) AS o0, (SELECT count(*) FROM lineitem) AS l0, (SELECT count(*) FROM j2) AS n2, (SELECT count(*) FROM j3) AS n3, (SELECT count(*) FROM j4) AS n4, (SELECT count(*) FROM r) AS nr, (SELECT count(DISTINCT doc_id % 25) FROM documents WHERE doc_id % 25 >= 0) AS g),
chains AS (SELECT sum(a + 3 * b + 4 * c) AS reads, sum(3 * b + 5 * c) AS writes FROM (SELECT * FROM c UNION ALL SELECT * FROM o UNION ALL SELECT * FROM s UNION ALL SELECT * FROM p))
SELECT 'staged' AS mode, CAST(chains.reads + (o0 + c.c) + (d.a + 3 * d.b + 3 * d.c + 2 * g) + (l0 + o.c + 2 * n2) + (n2 + p.c + 2 * n3) + (n3 + s.c) + n4 + 2 * nr + (nr + g) + nr AS BIGINT) AS reads,
    CAST(chains.writes + o.a + (3 * d.b + 3 * d.c + 3 * g) + 3 * n2 + 3 * n3 + n4 + 3 * nr + 2 * nr AS BIGINT) AS writes, 52 AS components FROM chains, c, o, s, p, d, k
UNION ALL SELECT 'fused', CAST(c.a + o0 + s.a + p.a + d.a + l0 + c.c + o.c + s.c + p.c + g + n2 + n3 + nr AS BIGINT), CAST(c.c + o.c + s.c + p.c + g + n2 + n3 + nr + nr AS BIGINT), 52 FROM c, o, s, p, d, k
"""


@query("big_pipeline_traffic", _TRAFFIC)
def big_pipeline_traffic(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Items read and written by the rules of cost.step_traffic, from the items that each component gives on the given tables."""
    p = big_pipeline(spark, sf_dir)
    items = pipeline.items_given(p, spark)
    files = {"customer", "orders", "supplier", "part", "documents", "lineitem"}
    rows = []
    for mode in ("staged", "fused"):
        steps = cost.step_traffic(p.graph, mode, files, {"give"}, items)
        rows.append((mode, sum(r for _, _, r, _ in steps), sum(w for _, _, _, w in steps), pipeline.component_count(p)))
    return spark.createDataFrame(rows, "mode string, reads long, writes long, components int")
