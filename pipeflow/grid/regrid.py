"""Regridding: target cell t takes the source's value at f(t). All methods return (tgt, v) in row-major files' order.

off_grid: "null" keeps target cells without a source cell, "drop" leaves them out, "error" refuses.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pipeflow.grid.mappings import CellMap
from pipeflow.grid.shape import div, to_tiles
from pipeflow.plans.memory import manual_three_phase
from pipeflow.session import fresh_path, materialise, partitions

#: Cells that a broadcast source may have: the driver holds their rows and a hash table of them at once, so far less than its heap.
BROADCAST_CELLS = 1 << 20


def pairs(spark: SparkSession, f: CellMap, parts: int | None = None) -> DataFrame:
    """(tgt, src) for every target cell: a range and a projection."""
    return spark.range(0, f.target.n, 1, parts or partitions(spark)).select(F.col("id").alias("tgt"), f.of(F.col("id")).cast("long").alias("src"))


def _kept(p: DataFrame, off_grid: str) -> DataFrame:
    if off_grid == "drop":
        return p.where("src is not null")
    if off_grid == "error":
        return p.withColumn("src", F.coalesce("src", F.raise_error(F.lit("a target cell lies off the source grid")).cast("long")))
    return p


def row_major(df: DataFrame, n: int, parts: int | None = None) -> DataFrame:
    """The last sort: cells go to the partition of their block by id, so no sampling job runs, and are sorted there."""
    k = parts or partitions(df.sparkSession)
    block = max(1, -(-n // k))
    return df.repartitionById(k, div(F.col("tgt"), block).cast("int")).sortWithinPartitions("tgt")


def triples(a: DataFrame, f: CellMap, off_grid: str = "null", how: str = "merge", parts: int | None = None) -> DataFrame:
    """(tgt, v) as the first sort's merge hands them over, before the last sort."""
    p = _kept(pairs(a.sparkSession, f, parts), off_grid)
    # off-grid cells don't travel to one partition: they need no partner
    met = p.where("src is not null").join(a.withColumnRenamed("cell", "src").hint(how), "src", "left").select("tgt", "v")
    if off_grid == "null":
        met = met.unionByName(p.where("src is null").select("tgt", F.lit(None).cast(a.schema["v"].dataType).alias("v")))
    return met


def fused(a: DataFrame, f: CellMap, off_grid: str = "null", how: str = "merge", parts: int | None = None) -> DataFrame:
    """The five steps as one lazy plan: two exchanges are the two sorts' runs, everything else is fused.

    A source that save_clustered() stored brings its order along and isn't exchanged. A source cell that very many
    targets share makes a hot key: adaptive execution splits it, since both sides are plain exchanges.
    """
    return row_major(triples(a, f, off_grid, how, parts), f.target.n, parts)


def direct(a: DataFrame, f: CellMap, off_grid: str = "null") -> DataFrame:
    """Each target cell looks its value up: a broadcast of the source, if it is small enough to be one; else fused."""
    if f.source.n > BROADCAST_CELLS:
        return fused(a, f, off_grid)
    p = _kept(pairs(a.sparkSession, f), off_grid)
    return p.join(F.broadcast(a.withColumnRenamed("cell", "src")), "src", "left").select("tgt", "v")


def plain_sql(a: DataFrame, f: CellMap) -> DataFrame:
    """What one would write without thought: join and order by. The sort samples, which runs the join twice."""
    return pairs(a.sparkSession, f).join(a.withColumnRenamed("cell", "src"), "src", "left").select("tgt", "v").orderBy("tgt")


def save_clustered(df: DataFrame, key: str, buckets: int) -> str:
    """A bucketed table sorted by key in the warehouse; its name."""
    name = f"clustered_{uuid.uuid4().hex}"
    df.repartition(buckets, key).write.bucketBy(buckets, key).sortBy(key).saveAsTable(name)
    return name


def clustered(a: DataFrame, f: CellMap, off_grid: str = "null") -> DataFrame:
    """Fused, on a source stored in row-major buckets: the source isn't exchanged."""
    spark = a.sparkSession
    name = save_clustered(a, "cell", partitions(spark))
    return fused(spark.table(name), f, off_grid)


def staged(a: DataFrame, f: CellMap) -> DataFrame:
    """The baseline: each of the five steps writes its list and the next reads it. Sorted lists are bucketed tables."""
    spark, k = a.sparkSession, partitions(a.sparkSession)
    source = spark.table(save_clustered(a, "cell", k)).withColumnRenamed("cell", "src")
    built = materialise(pairs(spark, f), "pairs")
    ordered = spark.table(save_clustered(built, "src", k))
    met = materialise(ordered.join(source.hint("merge"), "src", "left").select("tgt", "v"), "triples")
    back = materialise(row_major(met, f.target.n), "back")
    return materialise(back, "grid")


def handmade_phases(a: DataFrame, f: CellMap, sort_parts: tuple[int, int, int] | None = None) -> DataFrame:
    """Three jobs, one a phase, with a list on disk at each blocking edge and nothing else."""
    spark = a.sparkSession
    one, two, three = sort_parts or (partitions(spark),) * 3
    runs = spark.table(save_clustered(pairs(spark, f, one), "src", two))
    source = spark.table(save_clustered(a, "cell", two)).withColumnRenamed("cell", "src")
    triples = materialise(runs.join(source.hint("merge"), "src", "left").select("tgt", "v"), "runs")
    return row_major(triples, f.target.n, three)


def manual(a: DataFrame, f: CellMap, memory: int, read_buffer: int, write_buffer: int, item_bytes: int = 16) -> DataFrame:
    """The manual baseline: the caller names the phases and splits the memory; a sorter's share gives its partitions."""
    cores = a.sparkSession.sparkContext.defaultParallelism
    split = manual_three_phase(memory, read_buffer, write_buffer)
    parts = tuple(max(1, min(10_000, -(-f.target.n * item_bytes * cores // share))) for share in (split[0], split[1], split[2]))
    return handmade_phases(a, f, parts)  # type: ignore[arg-type]


def tiled(a: DataFrame, f: CellMap, tile: int) -> DataFrame:
    """The source travels as arrays of `tile` cells: its exchange carries n / tile rows."""
    tiles = to_tiles(a, tile)
    p = pairs(a.sparkSession, f).withColumn("tile", div(F.col("src"), tile))
    at = F.expr(f"get(vals, cast(src % {tile} as int))")
    return row_major(p.join(tiles, "tile", "left").select("tgt", at.alias("v")), f.target.n)


def tile_pruned(a: DataFrame, f: CellMap, tile: int) -> DataFrame:
    """Source tiles go to the target tiles that touch them; pairs are made again there and never sorted."""
    p = pairs(a.sparkSession, f)
    touched = p.where("src is not null").select(div(F.col("tgt"), tile).alias("to"), div(F.col("src"), tile).alias("tile")).distinct()
    got = touched.join(to_tiles(a, tile), "tile").groupBy("to").agg(F.map_from_entries(F.collect_list(F.struct("tile", "vals"))).alias("tiles"))
    every = a.sparkSession.range(0, -(-f.target.n // tile)).withColumnRenamed("id", "to")
    cells = every.join(got, "to", "left").select("tiles", F.explode(F.expr(f"sequence(to * {tile}, least((to + 1) * {tile}, {f.target.n}L) - 1)")).alias("tgt")).withColumn("src", f.of(F.col("tgt")))
    at = F.expr(f"get(try_element_at(tiles, src div {tile}L), cast(src % {tile} as int))")
    return row_major(cells.select("tgt", at.alias("v")), f.target.n)


def align(grids: list[tuple[DataFrame, CellMap]]) -> DataFrame:
    """(cell, v1 .. vk): several grids brought to one target shape, one row a target cell, null where a grid has no value.

    Each grid's triples carry its own column; together they are exchanged by cell once, and meet there. A source with
    several rows for one cell contributes any one of their values.
    """
    names = [f"v{k}" for k in range(1, len(grids) + 1)]
    types = [a.schema["v"].dataType for a, _ in grids]
    out = None
    for k, (a, f) in enumerate(grids):
        own = [F.col("v").alias(n) if i == k else F.lit(None).cast(t).alias(n) for i, (n, t) in enumerate(zip(names, types, strict=True))]
        one = triples(a, f).select(F.col("tgt").alias("cell"), *own)
        out = one if out is None else out.unionByName(one)
    # without the repartition, an aggregation before the exchange would hash every triple and merge none
    return out.repartition("cell").groupBy("cell").agg(*[F.any_value(n, ignoreNulls=True).alias(n) for n in names])


def write_grid(grid: DataFrame, path: str) -> None:
    """One file a target block, in row-major order by file name."""
    grid.write.parquet(path)


def round_trip(grid: DataFrame) -> DataFrame:
    path = fresh_path(grid.sparkSession, "grid")
    write_grid(grid, path)
    return grid.sparkSession.read.schema(grid.schema).parquet(path)
