"""MinHash near-deduplication: one-permutation hashing with optimal densification, banded buckets, star-shaped edges.

A document's set holds the hashes of its distinct k-word shingles (A-Z in lower case; fewer words: the whole sequence;
no words: empty, linked with nothing). Documents with equal sets are one class. A class has one permutation's minimum
in each of `bins` bins; an empty bin borrows that of a bin drawn by a hash of (bin, attempt), the same for all
documents. Rows of bins are banded; documents that share a band share a bucket.

Within a bucket edges form stars: members are tried against centres, not against each other, and only where the two lie
in different components and their sizes allow a link. Links are confirmed on full sets. In the first round a bucket has
one centre; buckets whose members still lie in two components or more go into another round with four times as many new
centres, those with the most confirmed links first. A bucket closes when its members are in one component or all have
been centres.

After `ROUNDS` rounds the members of the buckets still open are closed exactly: with all sets in one order of shingles,
the rare ones first, two sets that reach the threshold share a shingle near their starts, and its places bound how much
more they can share (`near_pairs`). What the bound rules out is no link; every other pair of two components is
confirmed on full sets, whatever the size of its bucket.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pipeflow.llm.common import LOWER, column, discard, ids_are_keys, is_marked, map_slices, marked_bits, only_marked, raw_texts, release, resident, saved, shingle_hashes, slices, slot, unused, without, word_hashes

#: 42 bands of 6 of the 256 bins: a pair that shares 80 % is in no common bucket with probability 3e-6, one of 40 % in one with 0.16.
BINS, ROWS, ATTEMPTS = 256, 6, 48
#: Rounds of stars before the buckets still open are closed exactly; counters of the shingles' frequencies, by hash.
ROUNDS, COUNTERS = 2, 1 << 20


def shingle_set(raw: bytes, k: int) -> np.ndarray:
    return np.unique(shingle_hashes(word_hashes(raw.translate(LOWER).split()), k))


def packed_set(shingles: np.ndarray) -> bytes:
    """The high 40 bits of each hash of a sorted set: two sets of thousands of shingles meet by chance in 1 of 10^5 cases."""
    return shingles.astype(">u8").view(np.uint8).reshape(-1, 8)[:, :5].tobytes()


def unpacked(raw: bytes) -> np.ndarray:
    wide = np.zeros((len(raw) // 5, 8), np.uint8)
    wide[:, 3:] = np.frombuffer(raw, np.uint8).reshape(-1, 5)
    return wide.reshape(-1).view(">u8").astype(np.int64)


def _probes(bins: int) -> np.ndarray:
    rng = np.random.default_rng(20)
    return rng.integers(0, bins, (bins, ATTEMPTS))


def signature(shingles: np.ndarray, bins: int = 128, probes: np.ndarray | None = None) -> np.ndarray:
    """The densified minima of a sorted set: bins are equal ranges of the hash, so a bin's minimum is its first value."""
    probes = _probes(bins) if probes is None else probes
    edges = (np.arange(bins, dtype=np.uint64) << np.uint64(64 - bins.bit_length() + 1)).astype(np.uint64)
    at = np.searchsorted(shingles, edges)
    full = np.append(at[1:], len(shingles)) > at
    source = np.arange(bins)
    empty = np.flatnonzero(~full)
    if len(empty):
        hit = full[probes[empty]]
        first = hit.argmax(axis=1)
        found = hit[np.arange(len(empty)), first]
        source[empty] = probes[empty, first]
        if not found.all():  # very few full bins: the nearest full one in a fixed turn
            ring = np.flatnonzero(full)
            late = empty[~found]
            source[late] = ring[(late * 7919) % len(ring)]
    return shingles[at[source]]


def band_keys(values: np.ndarray, rows: int = ROWS) -> list[int]:
    raw = values.astype("<u8").tobytes()
    return [xxhash.xxh3_64_intdigest(raw[i : i + 8 * rows], seed=i) - (1 << 63) for i in range(0, len(raw) - 8 * rows + 1, 8 * rows)]


SETS = "row long, local long, n_shingles long, set_hi long, set_lo long, bands array<long>"


def sets(docs: DataFrame, k: int, bins: int = BINS, rows: int = ROWS, room: int = 1_000_000) -> DataFrame:
    """docs (row, text) -> each document's set size and the row that its task met first with the same set; that row has the band keys."""

    def make():
        resident()
        probes = _probes(bins)
        met: dict[int, int] = {}

        def one(part):
            out: list[list] = [[] for _ in range(6)]
            for row, raw in zip(column(part, "row").to_pylist(), raw_texts(part), strict=True):
                s = shingle_set(raw, k)
                if not len(s):
                    values = (row, row, 0, None, None, None)
                else:
                    d = xxhash.xxh3_128_intdigest(s.astype("<u8").tobytes())
                    local = met.setdefault(d, row)
                    if local == row:
                        values = (row, row, len(s), (d >> 64) - (1 << 63), (d & (1 << 64) - 1) - (1 << 63), band_keys(signature(s, bins, probes), rows))
                    else:
                        values = (row, local, len(s), None, None, None)
                for c, v in zip(out, values, strict=True):
                    c.append(v)
            if len(met) > room:
                met.clear()
            types = (pa.int64(),) * 5 + (pa.list_(pa.int64()),)
            return {n: pa.array(c, t) for n, c, t in zip(("row", "local", "n_shingles", "set_hi", "set_lo", "bands"), out, types, strict=True)}

        return one

    return map_slices(docs, SETS, make)


def full_sets(docs: DataFrame, ids: DataFrame, k: int) -> DataFrame:
    """(row, shingles) of the documents whose row is in ids, and perhaps of a few more."""

    def make():
        return lambda part: {"row": column(part, "row"), "shingles": pa.array([packed_set(shingle_set(x, k)) for x in raw_texts(part)], pa.binary())}

    words = marked_bits(ids)
    if words is None:
        return map_slices(only_marked(docs, "row", ids), "row long, shingles binary", make)
    return map_slices(docs, "row long, shingles binary", make, ("row", words))


def confirmed(pairs: DataFrame, percent: int) -> DataFrame:
    """pairs (a, b, sa, sb: packed sorted sets) -> (a, b) with 100 * intersection >= percent * union."""

    def make():
        def test(part):
            keep = []
            for x, y in zip(column(part, "sa").to_pylist(), column(part, "sb").to_pylist(), strict=True):
                if 100 * min(len(x), len(y)) < percent * max(len(x), len(y)):
                    keep.append(False)
                    continue
                p, q = unpacked(x), unpacked(y)
                both = np.sort(np.concatenate([p, q]))
                n = int((both[1:] == both[:-1]).sum())
                keep.append(100 * n >= percent * (len(p) + len(q) - n))
            mask = pa.array(keep, pa.bool_())
            return pa.RecordBatch.from_pydict({"a": column(part, "a").filter(mask), "b": column(part, "b").filter(mask)})

        return test

    return map_slices(pairs, "a long, b long", make)


def linked(pairs: DataFrame, packed: DataFrame, percent: int) -> DataFrame:
    """pairs (id, centre) -> (a, b), the links among them. A member's set is sent to its centre; of the other sets only the centres' are shuffled."""
    members = pairs.join(packed.select(F.col("row").alias("id"), F.col("shingles").alias("sa")), "id")
    centres = only_marked(packed, "row", pairs.select("centre").distinct()).select(F.col("row").alias("centre"), F.col("shingles").alias("sb"))
    both = members.join(centres, "centre").select(F.col("id").alias("a"), F.col("centre").alias("b"), "sa", "sb")
    return saved(confirmed(both, percent), "links")


def members(made: DataFrame, shared: DataFrame) -> DataFrame:
    """made (row, n_shingles, bands) -> (id, n, key): a row for each band whose key is in shared, and perhaps for a few more."""
    words = marked_bits(shared)
    if words is None:
        return made.select(F.col("row").alias("id"), F.col("n_shingles").alias("n"), F.explode("bands").alias("key"))
    sent = made.sparkSession.sparkContext.broadcast(words)

    def make():
        def one(part):
            bands = column(part, "bands")
            key = bands.flatten().to_numpy(zero_copy_only=False)
            of = np.repeat(np.arange(part.num_rows), np.diff(bands.offsets.to_numpy()))
            at = np.flatnonzero(is_marked(key, sent.value)) if len(key) else np.zeros(0, np.int64)
            pick = pa.array(of[at])
            return {"id": column(part, "row").take(pick), "n": column(part, "n_shingles").take(pick), "key": pa.array(key[at].astype(np.int64))}

        return one

    return map_slices(made, "id long, n long, key long", make)


def components(edges: DataFrame) -> DataFrame:
    """edges (a, b) -> (id, comp): the least id that each end of an edge reaches.

    Rounds of least labels with pointer jumping. Tables that meet in a join are saved first, so that Spark can split
    the tasks of a label or a hub that many rows share.
    """
    both = saved(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "edges")
    state = saved(both.select(F.col("a").alias("id")).distinct().withColumn("comp", F.col("id")), "comp")
    while True:
        near = saved(both.join(state.withColumnRenamed("id", "b"), "b").groupBy(F.col("a").alias("id")).agg(F.min("comp").alias("near")), "near")
        hook = saved(state.join(near, "id").groupBy("comp").agg(F.min(F.least("comp", "near")).alias("to")), "hook")
        moves = saved(hook.join(hook.select(F.col("comp").alias("to"), F.col("to").alias("next")), "to", "left").select("comp", F.coalesce("next", "to").alias("to")).where("to != comp"), "moves")
        if not moves.limit(1).count():
            for x in (both, near, hook, moves):
                discard(x)
            return state
        new = saved(state.join(moves, "comp", "left").select("id", F.coalesce("to", "comp").alias("comp")), "comp")
        for x in (state, near, hook, moves):
            discard(x)
        state = new


def frequencies(packed: DataFrame) -> np.ndarray:
    """How many of the packed sets hold a shingle, by the shingle's slot; slots that shingles share count all of them."""

    def count(batches):
        seen = np.zeros(COUNTERS, np.int64)
        for part in slices(batches):
            at, n = np.unique(slot(unpacked(b"".join(column(part, "shingles").to_pylist())), COUNTERS), return_counts=True)
            seen[at] += n
        at = np.flatnonzero(seen)
        yield pa.RecordBatch.from_pydict({"slot": pa.array(at.astype(np.int32)), "n": pa.array(seen[at])})

    table = packed.select("shingles").mapInArrow(count, "slot int, n long").groupBy("slot").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(COUNTERS, np.int64)
    out[table.column("slot").to_numpy()] = table.column("n").to_numpy()
    return out


def heads(packed: DataFrame, percent: int) -> DataFrame:
    """packed (id, comp, shingles) -> (id, comp, n, at, token): the shingles by which a set can first meet one that it links with.

    The order is by frequency, then by hash. A link shares percent / 100 of either set at least, so its first common
    shingle is no later than what remains. Shingles of one set only are left out; they keep their places.
    """
    shared = packed.sparkSession.sparkContext.broadcast(frequencies(packed))

    def make():
        def one(part):
            out = [[] for _ in range(5)]
            for i, comp, raw in zip(column(part, "id").to_pylist(), column(part, "comp").to_pylist(), column(part, "shingles").to_pylist(), strict=True):
                s = unpacked(raw)
                n = len(s)
                often = shared.value[slot(s, COUNTERS)]
                order = np.lexsort((s, often))[: n - -(-percent * n // 100) + 1]
                at = np.flatnonzero(often[order] > 1)
                for c, v in zip(out, (np.full(len(at), i), np.full(len(at), comp), np.full(len(at), n), at, s[order[at]]), strict=True):
                    c.append(v.astype(np.int64))
            return {k: pa.array(np.concatenate(c), pa.int64()) for k, c in zip(("id", "comp", "n", "at", "token"), out, strict=True)}

        return one

    return map_slices(packed, "id long, comp long, n long, at long, token long", make)


def near_pairs(packed: DataFrame, percent: int) -> DataFrame:
    """packed (id, comp, shingles) -> (a, b): every pair of two components that may reach the threshold, once.

    At the first common shingle of two sets all that they share lies at or after its places. Members of a shingle's
    commonest component aren't held against each other: each pair of two components has a member outside of it.
    """
    made = saved(heads(packed, percent), "heads")
    by = made.groupBy("token", "comp").agg(F.count("*").alias("c")).groupBy("token").agg(F.max_by("comp", F.struct("c", "comp")).alias("top"), F.count("*").alias("kinds"))
    live = saved(made.join(by.where("kinds > 1").select("token", "top"), "token").withColumn("minor", F.col("comp") != F.col("top")).drop("top"), "live")
    x = live.where("minor").select("token", F.col("id").alias("xi"), F.col("comp").alias("xc"), F.col("n").alias("xn"), F.col("at").alias("xa"))
    most = F.least(F.col("n") - F.col("at"), F.col("xn") - F.col("xa"))
    may = (F.col("comp") != F.col("xc")) & (~F.col("minor") | (F.col("xi") < F.col("id"))) & (100 * F.least("n", "xn") >= percent * F.greatest("n", "xn")) & ((100 + percent) * most >= percent * (F.col("n") + F.col("xn")))
    out = saved(live.withColumnRenamed("token", "t").join(x, (F.col("t") == F.col("token")) & may).select(F.least("id", "xi").alias("a"), F.greatest("id", "xi").alias("b")).distinct(), "near-pairs")
    for y in (made, live):
        discard(y)
    return out


def classes(docs: DataFrame, k: int = 5, percent: int = 80, bins: int = BINS, rows: int = ROWS, rounds: int = ROUNDS) -> DataFrame:
    """docs (row, text), rows distinct, not null -> row, n_shingles, component: the least row that it is linked with, directly or not."""
    spark = docs.sparkSession
    made = saved(sets(docs, k, bins, rows), "sets")
    first = made.where("row = local and n_shingles > 0").select("row", "set_hi", "set_lo")
    reps = saved(first.groupBy("set_hi", "set_lo").agg(F.min("row").alias("rep")), "reps")
    owner = saved(first.join(reps, ["set_hi", "set_lo"]).select(F.col("row").alias("local"), "rep"), "owner")
    banded = saved(made.where("bands is not null").select("row", "n_shingles", "bands").join(reps.select(F.col("rep").alias("row")), "row"), "bands")
    shared = saved(banded.select(F.explode("bands").alias("key")).groupBy("key").agg(F.count("*").alias("size")).where("size > 1").select("key"), "shared")
    release(spark)
    found = saved(members(banded, shared), "members")
    open_ = saved(found.join(shared, "key").select("key", "id", "n", F.col("id").alias("comp"), F.lit(False).alias("done")), "buckets")
    for x in (reps, banded, shared, found):
        discard(x)
    packed = saved(full_sets(docs, open_.select("id").distinct(), k), "packed")
    nothing = packed.select(F.col("row").alias("a"), F.col("row").alias("b")).where("false")
    made_links: list[DataFrame] = []
    labels = nothing.select(F.col("a").alias("id"), F.col("b").alias("comp"))
    degree = nothing.select(F.col("a").alias("id"), F.col("b").alias("links"))
    centres, turn = 1, 0
    while turn < rounds and open_.limit(1).count():
        # centres: not yet one in this bucket, most links first, then by a hash that differs by round; each task sends no more than it may give
        order = Window.partitionBy("key").orderBy(F.col("done"), F.coalesce("links", F.lit(0)).desc(), F.xxhash64("id", F.lit(turn)), "id")
        ranked = open_.join(degree, "id", "left").withColumn("r", F.row_number().over(order)).where(F.col("r") <= centres)
        best = saved(ranked.where("not done").select("key", F.col("id").alias("centre"), F.col("n").alias("cn"), F.col("comp").alias("ccomp")), "centres")
        # a pair is made only if it may be a link that joins two components
        may = (F.col("comp") != F.col("ccomp")) & (100 * F.least("n", "cn") >= percent * F.greatest("n", "cn"))
        rows_, heads_ = open_.select(F.col("key").alias("k"), "id", "n", "comp"), best.withColumnRenamed("key", "h")
        star = saved(rows_.join(heads_, (F.col("k") == F.col("h")) & may).select("id", "centre").distinct(), "star")
        fresh = linked(star, packed, percent)
        made_links.append(fresh)
        if fresh.limit(1).count():
            every = nothing
            for x in made_links:
                every = every.unionByName(x)
            discard_all(labels, degree)
            labels = components(every)
            degree = saved(every.select(F.col("a").alias("id")).union(every.select("b")).groupBy("id").agg(F.count("*").alias("links")), "degree")
        was = best.select("key", F.col("centre").alias("id"), F.lit(True).alias("now"))
        after = open_.drop("comp").join(was, ["key", "id"], "left").join(labels, "id", "left").select("key", "id", "n", F.coalesce("comp", "id").alias("comp"), (F.col("done") | F.col("now").isNotNull()).alias("done"))
        after = saved(after, "after")
        # open: members in different components, and pairs of them that haven't met
        still = saved(after.groupBy("key").agg(F.min("comp").alias("low"), F.max("comp").alias("high"), F.sum((~F.col("done")).cast("int")).alias("left")).where("low != high and left > 1").select("key"), "still")
        before, open_ = open_, saved(after.join(still, "key"), "buckets")
        discard_all(before, best, star, after, still)
        release(spark)
        centres, turn = 4 * centres, turn + 1
    if open_.limit(1).count():
        left = saved(open_.select("id", "comp").distinct().join(packed.select(F.col("row").alias("id"), "shingles"), "id"), "left")
        tried = near_pairs(left, percent)
        made_links.append(linked(tried.select(F.col("a").alias("id"), F.col("b").alias("centre")), packed, percent))
        every = nothing
        for x in made_links:
            every = every.unionByName(x)
        discard_all(labels)
        labels = components(every)
        discard_all(left, tried)
    out = owner.join(labels.select(F.col("id").alias("rep"), "comp"), "rep", "left").select("local", F.coalesce("comp", "rep").alias("comp"))
    out = saved(made.select("row", "local", "n_shingles").join(out, "local", "left").select("row", "n_shingles", F.coalesce("comp", "row").alias("component")), "classes")
    discard_all(made, owner, packed, open_, labels, degree, *made_links)
    release(spark)
    return out


def discard_all(*tables: DataFrame) -> None:
    for x in tables:
        if hasattr(x, "pipeflow_path"):
            discard(x)


def components_of(docs: DataFrame, k: int, percent: int = 80) -> DataFrame:
    """docs (doc_id, text) -> doc_id, n_shingles, component_id, kept.

    Rows that repeat an id, or have none, are documents of their own; component_id is the least id in the component
    and kept holds for the rows that bear it. A component of null ids alone has a null component_id.
    """
    docs = docs.select(F.col("doc_id").cast("long"), "text")
    if ids_are_keys(docs):
        out = classes(docs.withColumnRenamed("doc_id", "row"), k, percent)
        return out.select(F.col("row").alias("doc_id"), "n_shingles", F.col("component").alias("component_id"), (F.col("row") == F.col("component")).alias("kept"))
    rows = saved(docs.withColumn("row", F.monotonically_increasing_id()), "rows")
    found = classes(rows.select("row", "text"), k, percent)
    out = saved(found.join(rows.select("row", "doc_id"), "row"), "with-ids")
    least = saved(out.groupBy("component").agg(F.min("doc_id").alias("component_id")), "least")
    discard_all(rows, found)
    return out.join(least, "component").select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))


def deduplicated(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """docs with one row of each component, all columns: that with the least doc_id; where ids are null or repeat, the first of the input."""
    row = unused(docs, "row")
    if ids_are_keys(docs):
        rows = docs.withColumn(row, F.col("doc_id").cast("long"))
    else:
        rows = saved(docs.withColumn(row, F.monotonically_increasing_id()), "near-rows")
    found = classes(rows.select(F.col(row).alias("row"), "text"), k, percent)
    return without(rows, row, found.where("row != component").select("row")).select(*docs.columns)
