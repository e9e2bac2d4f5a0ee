"""Mixing sources to target weights by a multivariate-hypergeometric splitting tree.

Each source's documents are permuted by a hash of their ids and dealt into blocks, which are ranges of that hash; a
block's size in words is exact, and a source has more blocks the more documents it has. A source's target is met by whole
passes over its blocks and one partial pass. A tree deals both out to output shards: a node splits its shards in halves
and draws how many blocks of each source the left half gets, by a multivariate hypergeometric, so that quotas stay exact
and shards keep the mix. In the partial pass a node also parts the source's permuted blocks among its halves, and a leaf
draws as many as its quota from the stretch that comes down to it: which documents the mix takes follows from the tree.

The partial pass' quota is the largest near target / block size whose drawn blocks don't exceed what is left of the
target. What then lacks is filled with blocks that no leaf has drawn, as long as they fit, and in the next one (the
edge) with documents in the order of the hash. Edges are taken apart twice by the hash, so a window is over a part of a block.
Within a shard rows have a random place.

Null sources are a source of their own, last; null texts have size 0. A source of size 0 has target 0. Null ids and
repeated rows count like other rows; the permutation orders equal hashes by id.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pipeflow.llm.common import ids_are_keys, saved, unused

WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS, SHARE, MOST_EPOCHS, SHARDS = (3, 1, 2), 1.5, 2.0, 64
#: Documents of a block, about, and blocks of a source at most; bits of the hash; parts of an edge block.
PER_BLOCK, BLOCKS, BITS, PARTS = 4, 1024, 48, 1024


def size_of(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def targets(sizes: list[int], weights: list[float], total: float, most: float = MOST_EPOCHS) -> list[float]:
    """total shared by weight; what a source can't take (more than `most` times its size) goes to the others by weight."""
    out, open_ = [0.0] * len(sizes), {i for i, s in enumerate(sizes) if s > 0}
    rest = total
    while open_:
        each = rest / sum(weights[i] for i in open_)
        over = {i for i in open_ if weights[i] * each > most * sizes[i]}
        for i in over or open_:
            out[i] = most * sizes[i] if over else weights[i] * each
        if not over:
            break
        rest -= sum(out[i] for i in over)
        open_ -= over
    return out


def deal(pools: list[np.ndarray], quotas: np.ndarray, shards: int, seed: list[int]) -> list[list[np.ndarray]]:
    """For each shard and source the items drawn: quotas[k] of pools[k] in all, shared out by a binary tree of multivariate hypergeometric draws."""
    out: list = [[] for _ in range(shards)]
    todo = [(0, shards, np.asarray(quotas, np.int64), pools)]
    while todo:
        first, n, have, pool = todo.pop()
        if n == 1:
            out[first] = [p[:q] for p, q in zip(pool, have.tolist(), strict=True)]
            continue
        left, total = n // 2, int(have.sum())
        rng = np.random.default_rng([*seed, first, n])
        take = rng.multivariate_hypergeometric(have, total * left // n, method="marginals") if total else have * 0
        # the stretch of a source's blocks is parted as its quota is; either half keeps as many as it must draw
        cuts = [min(max(round(len(p) * a / q) if q else 0, a), len(p) - (q - a)) for p, q, a in zip(pool, have.tolist(), take.tolist(), strict=True)]
        todo += [(first, left, take, [p[:c] for p, c in zip(pool, cuts, strict=True)]), (first + left, n - left, have - take, [p[c:] for p, c in zip(pool, cuts, strict=True)])]
    return out


def split(counts: np.ndarray, shards: int, seed: int) -> np.ndarray:
    """Blocks of each source for each shard. counts: one a source."""
    dealt = deal([np.arange(n) for n in counts], counts, shards, [seed])
    return np.array([[len(x) for x in row] for row in dealt], np.int64).reshape(shards, len(counts))


def partial_pass(sizes: list[np.ndarray], rests: list[float], shards: int, seed: int) -> tuple[list[list[np.ndarray]], list[tuple[int, float] | None]]:
    """Blocks that the shards draw of each source, and its edge: a block and the words that it may still give.

    sizes[k]: words of the source's blocks; rests[k]: words to be drawn, less than their sum.
    """
    pools = [np.random.default_rng([seed, k, 7]).permutation(len(x)) for k, x in enumerate(sizes)]
    mean = [max(x.mean(), 1e-9) if len(x) else 1.0 for x in sizes]
    quotas = np.array([min(int(r / m), len(x)) if r > 0 else 0 for r, m, x in zip(rests, mean, sizes, strict=True)], np.int64)
    while True:
        dealt = deal(pools, quotas, shards, [seed])
        words = [sum(int(x[row[k]].sum()) for row in dealt) for k, x in enumerate(sizes)]
        over = [k for k, r in enumerate(rests) if quotas[k] and words[k] > r]
        if not over:
            break
        for k in over:
            quotas[k] = max(0, quotas[k] - max(1, int((words[k] - rests[k]) / mean[k])))
    more, edges = [], []
    for k, x in enumerate(sizes):
        drawn = set(np.concatenate([row[k] for row in dealt]).tolist()) if quotas[k] else set()
        rest, take, edge = rests[k] - words[k], [], None
        for b in pools[k].tolist() if rests[k] > 0 else ():
            if b in drawn:
                continue
            if x[b] > rest:
                edge = (b, rest)
                break
            take.append(b)
            rest -= int(x[b])
        # the edge goes to a shard like a block
        more.append(np.array(take + ([edge[0]] if edge else []), np.int64))
        edges.append(edge)
    extra = deal(more, np.array([len(x) for x in more], np.int64), shards, [seed, 1])
    return [[np.concatenate([a, b]) for a, b in zip(x, y, strict=True)] for x, y in zip(dealt, extra, strict=True)], edges


def _source_table(sized: DataFrame, weights: tuple, share: float, blocks: int) -> list[tuple]:
    """One row a source: source, source_size, target, blocks."""
    rows = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n")).collect()
    rows.sort(key=lambda r: (r.source is None, (r.source or "").encode()))
    sizes = [int(r.source_size) for r in rows]
    goal = targets(sizes, [weights[i % len(weights)] for i in range(len(rows))], share * sum(sizes))
    return [(r.source, s, float(t), min(blocks, 1 << max(0, (r.n // PER_BLOCK).bit_length() - 1))) for r, s, t in zip(rows, sizes, goal, strict=True)]


def _joined(left: DataFrame, rows: list[tuple], schema: str, *keys: str) -> DataFrame:
    """left with a small table's columns, matched on keys (null matches null). Its rows are few by source; it is broadcast only while they are."""
    table = left.sparkSession.createDataFrame(rows, schema)
    table = table.select(*(F.col(c).alias(f"{c}_") if c in keys else F.col(c) for c in table.columns))
    on = F.lit(True)
    for k in keys:
        on = on & left[k].eqNullSafe(table[f"{k}_"])
    return left.join(F.broadcast(table) if len(rows) <= 200_000 else table, on, "left").drop(*(f"{k}_" for k in keys))


def draw(docs: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, blocks: int = BLOCKS, shards: int = SHARDS, seed: int = 0) -> DataFrame:
    """docs (doc_id, text, source) -> a row a document: doc_id, size, source, source_size, target, block, copies, shard, place.

    copies: times the mix holds the document (0 to 2); shard, place: arrays, one entry a copy. The sums by source and
    block are what the driver sees: at most `blocks` rows a source, whatever the number of documents.
    """
    key = F.conv(F.substring(F.md5(F.concat(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit(f"/{seed}")).cast("binary")), 1, BITS // 4), 16, 10).cast("long")
    sized = saved(docs.select(F.col("doc_id").cast("long"), "source", size_of(F.col("text")).alias("size"), key.alias("key")), "sized")
    goals = _source_table(sized, weights, share, blocks)
    dealt_out = _joined(sized, goals, "source string, source_size long, target double, blocks int", "source").withColumn("block", F.expr(f"cast(key div ({1 << BITS} div blocks) as int)"))
    per: dict = {g[0]: [] for g in goals}
    for r in dealt_out.groupBy("source", "block").agg(F.sum("size").alias("n")).collect():
        per[r.source].append((r.block, int(r.n)))
    names, sizes, whole, rests = [], [], [], []
    for source, size, target, _ in goals:
        found = sorted(per[source])
        names.append(np.array([b for b, _ in found], np.int64))
        sizes.append(np.array([n for _, n in found], np.int64))
        whole.append(min(math.floor(target / size + 1e-12), 2) if size else 0)
        rests.append(max(0.0, target - whole[-1] * size))
    shard_of: dict = {}
    for epoch in range(max(whole, default=0)):
        pools = [np.random.default_rng([seed, k, epoch]).permutation(len(x)) if epoch < whole[k] else np.zeros(0, np.int64) for k, x in enumerate(sizes)]
        _note(shard_of, deal(pools, np.array([len(x) for x in pools], np.int64), shards, [seed, 2, epoch]))
    drawn, edges = partial_pass(sizes, rests, shards, seed) if goals else ([], [])
    _note(shard_of, drawn)
    rows, cut = [], {}
    for k, (source, *_) in enumerate(goals):
        edge = edges[k]
        for i, b in enumerate(names[k].tolist()):
            to = shard_of.get((k, i), [])
            if edge and edge[0] == i:
                cut[(source, b)] = edge[1]
            if to:
                rows.append((source, b, len(to) - (edge is not None and edge[0] == i), to))
    joined = _joined(dealt_out, rows, "source string, block int, passes int, shards array<int>", "source", "block").withColumn("passes", F.coalesce("passes", F.lit(0)))
    joined = joined.withColumn("part", F.expr(f"cast(key % ({1 << BITS} div blocks) div greatest(({1 << BITS} div blocks) div {PARTS}, 1) as int)"))
    # an edge's words by part: at most PARTS rows a source; the part where the rest ends is the only one that is sorted
    inner = _joined(joined, [(s, b, 1) for s, b in cut], "source string, block int, edge int", "source", "block")
    found = sorted((r.source is None, r.source or "", r.block, r.part, int(r.n)) for r in inner.where("edge = 1").groupBy("source", "block", "part").agg(F.sum("size").alias("n")).collect()) if cut else []
    parts, left = [], {}
    for none, name, block, part, n in found:
        source = None if none else name
        rest = left.get((source, block), cut[(source, block)])
        if rest is None:
            continue
        fits = n <= rest
        parts.append((source, block, part, fits, None if fits else float(rest)))
        left[(source, block)] = rest - n if fits else None
    fine = _joined(joined, parts, "source string, block int, part int, fits boolean, rest double", "source", "block", "part")
    w = Window.partitionBy("source", "block").orderBy(F.col("key"), F.col("doc_id").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    calm = fine.where("rest is null").withColumn("copies", F.col("passes") + F.coalesce(F.col("fits").cast("int"), F.lit(0)))
    last = fine.where("rest is not null").withColumn("copies", F.col("passes") + (F.sum("size").over(w) <= F.col("rest")).cast("int"))
    place = F.expr(f"transform(sequence(1, copies), i -> xxhash64(key, i, {seed}))")
    return calm.unionByName(last).select("doc_id", "size", "source", "source_size", "target", "block", "copies", F.when(F.col("copies") > 0, F.expr("slice(shards, 1, copies)")).alias("shard"), F.when(F.col("copies") > 0, place).alias("place"))


def _note(shard_of: dict, dealt: list) -> None:
    for shard, row in enumerate(dealt):
        for k, items in enumerate(row):
            for i in items.tolist():
                shard_of.setdefault((k, i), []).append(shard)


def mix(docs: DataFrame, **options) -> DataFrame:
    """The mixed dataset: docs' columns, a row for each copy that is drawn, in its shard's partition and at its place.

    The draw is made on doc_id (on a row's number in a table of its own where doc_id isn't a key), text and source.
    """
    spark = docs.sparkSession
    row, to = unused(docs, "row"), unused(docs, "to")
    if ids_are_keys(docs):
        kept = docs.withColumn(row, F.col("doc_id").cast("long"))
    else:
        kept = saved(docs.withColumn(row, F.monotonically_increasing_id()), "mix")
    picks = draw(kept.select(F.col(row).alias("doc_id"), "text", "source"), **options)
    rows = picks.where("copies > 0").select(F.col("doc_id").alias(row), F.explode(F.arrays_zip("shard", "place")).alias(to))
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    joined = kept.join(rows, row)
    return joined.repartition(n, f"{to}.shard", F.pmod(F.col(f"{to}.place"), F.lit(16))).sortWithinPartitions(f"{to}.shard", f"{to}.place").select(*docs.columns)


def digest(docs: DataFrame, **options) -> DataFrame:
    """docs (doc_id, text, source) -> doc_id, size, source_size, target, taken, shard, place: what the drawn blocks of the tree's shards hold of each document."""
    taken = F.col("size") * F.coalesce(F.size("shard"), F.lit(0))
    return draw(docs, **options).select("doc_id", "size", "source_size", F.round("target", 3).alias("target"), F.when(F.col("copies") > 0, taken).otherwise(0).cast("long").alias("taken"), "shard", "place")
