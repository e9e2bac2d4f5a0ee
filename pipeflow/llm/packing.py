"""Best-fit packing of token sequences by bulk-synchronous sweeps.

Documents are cut into pieces of at most `capacity` tokens. Pieces are taken by classes of size, each from its largest
waiting size down to half of it, and a class in sweeps. In a sweep its pieces and the gaps of all sequences are
range-sorted on one line, largest first. A piece takes its successor, the smallest gap that holds it and that no larger
piece has taken; so gaps open and pieces close a bracket, and each bracket's partner is the next one on its level. Every
task pairs the brackets of its range; those left over are paired across ranges by their level, on which each range has
at most one piece and one gap, by the rank of the ranges. A gap that holds several pieces of the largest size opens as
many brackets. Then the gaps are updated, and pieces still waiting are swept again; where none found a gap, sequences are
opened. Pairs don't depend on how the line is cut into ranges.

Nothing about single pieces or gaps comes to the driver: it sees counts by size (at most `capacity`) and by range.
There are at most log2(capacity) + 1 classes; a sweep that leaves pieces waiting uses up every bracket, which halves the
gaps that hold several.

Null texts are empty and take one token, the end id. Null ids and repeated rows are packed like any row: each is a
document of its own. Columns beside doc_id and text are not read.
"""

from __future__ import annotations

import zlib
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pipeflow.llm.common import column, discard, map_slices, saved, small_batches
from pipeflow.llm.tokens import encoder

CAPACITY, END = 4096, b"\x01\x00\x00\x00"
#: Pieces and gaps in a range of a sweep, which one task holds as arrays; brackets a gap's row opens at most (a wider gap has several rows).
RANGE, BRACKETS = 1 << 18, 16

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def pieces(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY) -> DataFrame:
    """Every document's ids with the end id, cut at the capacity."""

    def make():
        enc = encoder(vocabulary)

        def cut(part):
            out: list[list] = [[], [], [], [], []]
            step = 4 * capacity
            for doc_id, packed in zip(column(part, "doc_id").to_pylist(), enc.ids([x or "" for x in column(part, "text").to_pylist()]), strict=True):
                packed += END
                for k, at in enumerate(range(0, len(packed), step)):
                    raw = packed[at : at + step]
                    for c, v in zip(out, (doc_id, k, at // 4, len(raw) // 4, zlib.crc32(raw)), strict=True):
                        c.append(v)
            types = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            return {n: pa.array(c, t) for n, c, t in zip(("doc_id", "piece", "start", "length", "ids_crc32"), out, types, strict=True)}

        return cut

    return map_slices(docs.select(F.col("doc_id").cast("long"), "text"), PIECES, make)


def pairs(closes: np.ndarray, brackets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of items in line, where pieces close one bracket and gaps open some: for each piece the gap it takes, or -1; each item's (first) level."""
    each = np.where(closes, 1, brackets)
    item = np.repeat(np.arange(len(closes)), each)
    down = closes[item]
    level = np.cumsum(np.where(down, -1, 1)) + down
    order = np.argsort(level, kind="stable")
    left, right = order[:-1], order[1:]
    met = ~down[left] & down[right] & (level[left] == level[right])
    gap_of = np.full(len(closes), -1)
    gap_of[item[right[met]]] = item[left[met]]
    return gap_of, level[np.cumsum(each) - each]


SWEPT = "part int, row long, length int, sequence_id long, level long, brackets int"


def swept(waiting: DataFrame, gaps: DataFrame, largest: int, ranges: int) -> DataFrame:
    """Each piece with the gap it finds in its range, or with its level; and the gaps' brackets that are left, as runs of levels."""
    room = F.greatest(F.lit(1), F.floor(F.col("gap") / largest)).cast("int")
    chunk = F.explode(F.sequence(F.lit(0), F.floor((room - 1) / BRACKETS).cast("int"))).alias("chunk")
    opening = gaps.select("sequence_id", "gap", room.alias("room"), chunk).select(F.col("gap").alias("size"), F.lit(False).alias("closes"), F.col("sequence_id").alias("id"), "chunk", F.least(F.lit(BRACKETS), F.col("room") - F.col("chunk") * BRACKETS).cast("int").alias("brackets"))
    line = opening.unionByName(waiting.select(F.col("length").alias("size"), F.lit(True).alias("closes"), F.col("row").alias("id"), F.lit(0).alias("chunk"), F.lit(0).alias("brackets")))
    keys = [F.col("size").desc(), "closes", "id", "chunk"]
    line = (line.repartitionByRange(ranges, *keys) if ranges > 1 else line.repartition(1)).sortWithinPartitions(*keys).withColumn("part", F.spark_partition_id())

    def sweep(batches):
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        table = pa.Table.from_batches(got)
        size, closes, ids, brackets, part = (table.column(c).to_numpy() for c in ("size", "closes", "id", "brackets", "part"))
        gap_of, level = pairs(closes, brackets)
        taken = gap_of[gap_of >= 0]
        rest = np.where(closes, 0, brackets - np.bincount(taken, minlength=len(ids)))
        alone = closes & (gap_of < 0)
        keep = np.flatnonzero(closes | (rest > 0) if ranges > 1 else closes)
        owner = np.where(closes, ids[gap_of], ids)
        yield pa.RecordBatch.from_pydict(
            {
                "part": pa.array(part[keep], pa.int32()),
                "row": pa.array(ids[keep], pa.int64(), mask=~closes[keep]),
                "length": pa.array(np.where(closes, size, 0)[keep], pa.int32()),
                "sequence_id": pa.array(owner[keep], pa.int64(), mask=alone[keep]),
                "level": pa.array(level[keep], pa.int64()),
                "brackets": pa.array(rest[keep], pa.int32()),
            }
        )

    small_batches(waiting.sparkSession)
    return line.mapInArrow(sweep, SWEPT)


def across(found: DataFrame) -> DataFrame | None:
    """Pieces that found no gap in their range, with the gap of another range or none. Gaps before them on their level, by the rank of the ranges."""
    alone = F.col("sequence_id").isNull()
    ends = found.groupBy("part").agg(F.sum("brackets").alias("up"), F.count_if(alone).alias("down"), F.min(F.when(alone, F.col("level"))).alias("low"), F.max(F.when(alone, F.col("level"))).alias("high")).orderBy("part").collect()
    before = [0, *accumulate(r["up"] - r["down"] for r in ends)]
    low = min((r["low"] + b for r, b in zip(ends, before, strict=False) if r["down"]), default=None)
    if low is None:
        return None
    high = max(r["high"] + b for r, b in zip(ends, before, strict=False) if r["down"])
    base = found.sparkSession.createDataFrame([(r["part"], b) for r, b in zip(ends, before, strict=False)], "part int, base long")
    at = found.where(alone | (F.col("brackets") > 0)).join(F.broadcast(base), "part").withColumn("level", F.col("level") + F.col("base"))
    first, last = F.greatest("level", F.lit(low)), F.least(F.col("level") + F.col("brackets") - 1, F.lit(high))
    opening = at.where(~alone).where(first <= last).select("part", "row", "length", "sequence_id", F.explode(F.sequence(first, last)).alias("level"))
    line = at.where(alone).select("part", "row", "length", "sequence_id", "level").unionByName(opening)
    w = Window.partitionBy("level").orderBy("part", F.col("row").isNull())
    return line.withColumn("sequence_id", F.lag("sequence_id").over(w)).where("row is not null").select("row", "length", "sequence_id")


PLACED = "row long, length int, sequence_id long"


def _waiting(found: DataFrame) -> tuple[int, int, int, int]:
    """Pieces without a sequence: how many, their tokens, the smallest and the largest."""
    alone = found.where("row is not null and sequence_id is null")
    return tuple(x or 0 for x in alone.agg(F.count("*"), F.sum("length"), F.min("length"), F.max("length")).first())


def matched(sizes: DataFrame, capacity: int = CAPACITY, span: int = RANGE) -> DataFrame:
    """sizes: a saved table (row, length) in order of length -> row, length, sequence_id."""
    spark = sizes.sparkSession
    counts = dict(sorted((r["length"], r["count"]) for r in sizes.groupBy("length").count().collect()))  # at most `capacity` rows
    opened = -(-sum(s * n for s, n in counts.items()) // capacity)  # no packing has fewer
    smallest = min(counts, default=1)

    def fresh(first: int, n: int) -> DataFrame:
        return spark.range(first, first + n).select(F.col("id").alias("sequence_id"), F.lit(capacity).cast("long").alias("gap"))

    gaps, paths, old, top = fresh(0, opened), [], [], capacity
    while any(s <= top for s in counts):
        top = max(s for s in counts if s <= top)
        least = min(s for s in counts if 2 * s > top)
        n, tokens, largest = sum(c for s, c in counts.items() if least <= s <= top), sum(s * c for s, c in counts.items() if least <= s <= top), top
        waiting = sizes.where(F.col("length").between(least, top))
        bottom = least
        while n:
            holding = sorted((r["gap"], r["count"]) for r in gaps.where(F.col("gap") >= least).groupBy("gap").count().collect())  # at most `capacity` rows
            if not holding:
                # as many as hold all of them side by side; of small pieces, what their tokens fill
                more = -(-n // (capacity // largest)) if 4 * largest > capacity else -(-tokens // capacity)
                gaps, opened = gaps.unionByName(fresh(opened, more)), opened + more
                continue
            # gaps that hold any piece stay unused beyond the first n brackets, smallest gaps first
            widest, brackets, rows = holding[-1][0], 0, n
            for gap, c in holding:
                rows += c * -(-max(1, gap // largest) // BRACKETS)
                brackets += c * (gap // largest)
                if brackets >= n:
                    widest = gap
                    break
            ranges = -(-rows // span)
            found = saved(swept(waiting, gaps.where(F.col("gap").between(least, widest)), largest, ranges), "swept")
            paths.append(found.pipeflow_path)
            late = across(found) if ranges > 1 else None
            rest = found
            if late is not None:
                rest = saved(late, "late")
                paths.append(rest.pipeflow_path)
            taken = found.where("row is not null and sequence_id is not null").select("sequence_id", "length")
            if late is not None:
                taken = taken.unionByName(rest.where("sequence_id is not null").select("sequence_id", "length"))
            n, tokens, least, largest = (0, 0, 0, 0) if ranges > 1 and late is None else _waiting(rest)
            waiting = rest.where("row is not null and sequence_id is null").select("row", "length")
            gaps = saved(gaps.unionByName(taken.select("sequence_id", (-F.col("length")).cast("long").alias("gap"))).groupBy("sequence_id").agg(F.sum("gap").alias("gap")).where(F.col("gap") >= smallest), "gaps")  # smaller ones hold nothing that is to come
            old.append(gaps)
            for table in old[:-1]:
                discard(table)
            del old[:-1]
        top = bottom - 1
    for table in old:
        discard(table)
    if not paths:
        return spark.createDataFrame([], PLACED)
    return spark.read.schema(PLACED).parquet(*paths).where("row is not null and sequence_id is not null")


def place(cut: DataFrame, capacity: int = CAPACITY, span: int = RANGE) -> DataFrame:
    """Pieces with their sequence and the place there: a sequence's pieces lie in order of size, at most `capacity` of them."""
    numbered = saved(cut.withColumn("row", F.monotonically_increasing_id()), "pieces")
    keys = [F.col("length").desc(), "row"]
    sizes = saved(numbered.select("row", F.col("length").cast("int").alias("length")).repartitionByRange(1 + numbered.count() // (4 * span), *keys).sortWithinPartitions(*keys), "sizes")
    found = matched(sizes, capacity, span)
    discard(sizes)
    before = Window.partitionBy("sequence_id").orderBy(F.col("length").desc(), "row").rowsBetween(Window.unboundedPreceding, -1)
    offset = F.coalesce(F.sum("length").over(before), F.lit(0)).cast("long").alias("offset")
    return numbered.join(found.select("row", "sequence_id"), "row").select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", offset)


def pack(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY) -> DataFrame:
    return place(pieces(docs, vocabulary, capacity), capacity)
