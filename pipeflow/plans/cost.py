"""Costs in the two-level model: block transfers, item traffic of plans, time from traffic."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pipeflow.grid.shape import div
from pipeflow.plans.graph import BLOCKING, INPUT, OUTPUT, FlowGraph
from pipeflow.plans.phases import identify


def scan_ios(n: int, b: int) -> int:
    return -(-n // b)


def scan_ios_col(n: Column, b: Column) -> Column:
    return div(n + b - 1, b)


def sort_ios(n: int, m: int, b: int) -> float:
    """(n/b) log_{m/b}(n/b), one pass at least."""
    return n / b * max(1.0, math.log(max(n / b, 1)) / math.log(m / b)) if n else 0.0


def external_sort_traffic(n: int, m: int, fan_in: int) -> tuple[int, int, int, int]:
    """Runs, merge passes, items read, items written."""
    if fan_in < 2:
        raise ValueError("a merge takes two runs at least")
    runs = left = -(-n // m)
    passes = 0
    while left > 1:
        left, passes = -(-left // fan_in), passes + 1
    moved = n * (passes + 1)
    return runs, passes, moved, moved


def hours(size: float, per_second: float) -> float:
    return size / per_second / 3600


def saving(staged: tuple[int, int], fused: tuple[int, int]) -> float:
    """The part of all items moved that fusion avoids."""
    return 1 - sum(fused) / sum(staged)


def step_traffic(g: FlowGraph, mode: str, files: set[str] = frozenset(), sinks: set[str] = frozenset(), items: dict[str, int] | None = None) -> list[tuple[str, int, int, int]]:
    """(component, phase, reads, writes). files: components that read an input file; sinks: that write one; items: how many each node gives.

    Without items, the lists are counted, each as one unit.

    Materialised: a component reads all that comes in and writes what it makes; a sorter also writes and reads its runs.
    Fused: only files are read, sinks written, and a blocking component writes and reads its list once.
    """
    phase = identify(g)
    kind = {n.name: n.kind for n in g.nodes}
    gives = items or dict.fromkeys(g.names, 1)
    into = {n: sum(gives[e.src] for e in g.streaming() if e.dst == n) for n in g.names}
    out = {n: any(e.src == n for e in g.edges) for n in g.names}
    rows = []
    for n in g.names:
        if mode == "fused":
            reads = gives[n] * ((n in files) + (kind[n] == OUTPUT))
            writes = gives[n] * ((n in sinks) + (kind[n] == INPUT))
        elif kind[n] == INPUT:  # reads its list, writes runs
            reads, writes = into[n], gives[n]
        elif kind[n] == OUTPUT:  # merges the runs, writes the list
            reads, writes = gives[n], gives[n]
        elif n in files:  # what reads a file is read from by its consumer directly
            reads, writes = 0, 0
        else:
            reads, writes = into[n], gives[n] if n in sinks or out[n] else 0
        rows.append((n, phase[n], reads, writes))
    return rows


#: The regridding plan by its five steps: nodes of regrid_graph() in each.
STEPS = {"src": 1, "map": 1, "S1i": 2, "S1o": 2, "rd": 3, "co": 3, "S2i": 4, "S2o": 4, "emit": 5, "wr": 5}


def item_traffic(spark: SparkSession, n: int, mode: str) -> DataFrame:
    """(step, phase, reads, writes) of the regridding plan in items. Staged steps are whole steps: what is inside one is fused."""
    from pipeflow.plans.graph import regrid_graph

    g = regrid_graph()
    phase = identify(g)
    if mode == "fused":
        rows = [(STEPS[c], p, r * n, w * n) for c, p, r, w in step_traffic(g, "fused", {"rd"}, {"wr"})]
    else:
        inside = lambda e: STEPS[e.src] == STEPS[e.dst]
        rows = []
        for c in g.names:
            reads = sum(e.dst == c and not inside(e) for e in g.streaming()) + (c == "rd") + (c in ("S1o", "S2o"))
            writes = int(any(e.src == c and not inside(e) for e in g.streaming()) and c != "rd") + (c in ("S1i", "S2i", "wr"))
            rows.append((STEPS[c], phase[c], reads * n, writes * n))
    df = spark.createDataFrame(rows, "step int, phase int, reads long, writes long")
    return df.groupBy("step", "phase").agg(F.sum("reads").alias("reads"), F.sum("writes").alias("writes"))


def count_block_ios(trace: DataFrame, b: int, cache_blocks: int = 1, chunk: int = 1 << 20) -> DataFrame:
    """trace (pos, cell): block transfers of a reader with an LRU cache -> one row (n, ios).

    A cache of one block holds a chunk's first block against the last of the chunk before. Larger caches are warmed: what
    the cache holds after a chunk are the last `cache_blocks` distinct blocks up to there, of the chunk itself or, where
    it has fewer, of chunks before it; these few are carried from chunk to chunk on the driver.
    """
    t = trace.withColumn("block", div(F.col("cell"), b)).withColumn("chunk", div(F.col("pos"), chunk))
    if cache_blocks == 1:
        w = Window.partitionBy("chunk").orderBy("pos")
        inside = t.withColumn("before", F.lag("block").over(w))
        ends = t.groupBy("chunk").agg(F.min_by("block", "pos").alias("first"), F.max_by("block", "pos").alias("last"))
        seams = ends.join(ends.select((F.col("chunk") + 1).alias("chunk"), F.col("last").alias("before")), "chunk").where("first = before").agg(F.count("*").alias("same"))
        total = inside.agg(F.count("*").alias("n"), F.count_if(F.col("before").isNull() | (F.col("before") != F.col("block"))).alias("misses"))
        return total.crossJoin(seams).select("n", (F.col("misses") - F.col("same")).alias("ios"))

    # a chunk's last distinct blocks, oldest first; what the cache holds before each chunk
    spark = trace.sparkSession
    newest = Window.partitionBy("chunk").orderBy(F.col("at").desc())
    tails = t.groupBy("chunk", "block").agg(F.max("pos").alias("at")).withColumn("r", F.row_number().over(newest)).where(F.col("r") <= cache_blocks)
    held: list[int] = []
    warm = []
    for chunk, blocks in tails.groupBy("chunk").agg(F.sort_array(F.collect_list(F.struct("at", "block"))).alias("last")).select("chunk", "last.block").orderBy("chunk").toLocalIterator():
        warm += [(chunk, k - len(held), b) for k, b in enumerate(held)]
        new = set(blocks)
        held = ([b for b in held if b not in new] + blocks)[-cache_blocks:]
    warm_rows = spark.createDataFrame(warm, "chunk long, pos long, block long").withColumn("warm", F.lit(True))

    def lru(pdf: pd.DataFrame) -> pd.DataFrame:
        held: dict[int, None] = {}
        misses = 0
        # warming rows come first: they fill the cache and count for nothing
        for block, warming in pdf.sort_values(["warm", "pos"], ascending=[False, True])[["block", "warm"]].itertuples(index=False):
            if block in held:
                del held[block]
            else:
                misses += not warming
                if len(held) >= cache_blocks:
                    del held[next(iter(held))]
            held[block] = None
        return pd.DataFrame({"n": [int((~pdf["warm"]).sum())], "misses": [misses]})

    rows = t.select(F.col("chunk").cast("long"), F.col("pos").cast("long"), F.col("block").cast("long"), F.lit(False).alias("warm")).unionByName(warm_rows)
    return rows.groupBy("chunk").applyInPandas(lru, "n long, misses long").agg(F.sum("n").alias("n"), F.sum("misses").alias("ios"))


def extrapolate(jobs: DataFrame, *keep: str) -> DataFrame:
    """jobs (n, m, b, bytes an item, bytes a second: n, m, b, item, speed) -> keep, n, runs, merges, staged_h, fused_h, saved_h for the regridding plan.

    Lists move 7 times in and out staged and 3 times fused if sorts merge once; each merge more or less moves the two sorts' lists once more or less.
    """
    df = jobs.select(*keep, *(F.col(c).cast("double").alias(c) for c in ("n", "m", "b", "item", "speed")))
    fan_in, runs = F.col("m") / F.col("b"), F.ceil(F.col("n") / F.col("m")).cast("long")
    about = F.ceil(F.log(runs.cast("double")) / F.log(fan_in))
    # the quotient of logarithms may lie just above a whole number of passes
    merges = F.when(runs <= 1, 0).when(runs <= fan_in, 1).when(runs <= F.pow(fan_in, about - 1), about - 1).otherwise(about).cast("long")
    h, more = F.col("n") * F.col("item") / F.col("speed") / 3600.0, 4 * (merges - 1)
    return df.select(*keep, "n", runs.alias("runs"), merges.alias("merges"), F.round(h * (14 + more), 4).alias("staged_h"), F.round(h * (6 + more), 4).alias("fused_h"), F.round(h * 8, 4).alias("saved_h"))
