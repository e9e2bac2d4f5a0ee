"""Suffix-array deduplication by a depth-limited radix sort of windows, most significant digit first.

A byte goes if a `WINDOW`-byte string that covers it also starts anywhere else. Suffixes are ordered only as deep as
the window; groups that are equal to that depth are exactly the repeated windows. The digits, coarsest first:

1. the window's anchor: its `GRAM`-byte substring of least hash, leftmost of equals. It depends on the window's bytes
   alone, so equal windows have equal anchors at equal offsets. Neighbouring windows share an anchor and form a run.
2. the whole run's bytes: runs that occur twice or more are repeated throughout (copies end here). Runs whose anchor
   no other run has hold no repeated window (most text ends here).
3. of the runs that are left, blocks of 16 offsets: a block whose bytes occur twice is repeated throughout; one whose
   core (what all its windows share) occurs once holds no repeated window.
4. of the blocks that are left, single windows.

Each pass is a count by key with map-side sums and a join back; keys pair the anchor's hash with the digit's, 128 bits
in all. No pass compares rows of a group with each other, and no group is gathered anywhere.

Beside the bytes, `passages` finds by the same digits the texts that have a run of words in common with another one,
however few bytes the run has: windows are then of words instead of bytes, and nothing is cut for them.

Null texts are empty; texts shorter than the window keep every byte. Null ids and repeated rows are texts of their own.
Other columns are not read.
"""

from __future__ import annotations

import hashlib
import re
from functools import cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pipeflow.llm.common import column, discard, map_slices, mixed, only_marked, raw_texts, release, saved, slices, without

WINDOW, GRAM, BLOCK = 400, 145, 16
OFFSETS = WINDOW - GRAM + 1  # 256
GROUP, STRETCH, PIECE = 1 << 16, 1 << 22, 1 << 18
TOP, LOW = np.uint64(0xFFFFFFFFFF000000), np.uint64(0xFFFFFF)


def gram_hashes(b: np.ndarray, k: int = GRAM) -> np.ndarray:
    """Polynomial hashes of every k-byte substring, put together from powers of two, then scrambled."""
    cur = (b.astype(np.uint64) + np.uint64(1)) * np.uint64(0xBF58476D1CE4E5B9)
    base, size, out, have, left = np.uint64(0x9E3779B97F4A7C15), 1, None, 0, k
    with np.errstate(over="ignore"):
        while left:
            if left & 1:
                if out is None:
                    out, have = cur, size
                else:
                    m = len(b) - have - size + 1
                    out = out[:m] * base + cur[have : have + m]
                    have += size
            left >>= 1
            if left:
                m = len(cur) - size
                cur = cur[:m] * base + cur[size : size + m]
                size, base = size * 2, base * base
        out = out[: len(b) - k + 1]
        out = (out ^ (out >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return out ^ (out >> np.uint64(32))


def sliding_least(a: np.ndarray, w: int) -> np.ndarray:
    size, cur = 1, a
    while 2 * size <= w:
        cur = np.minimum(cur[:-size], cur[size:])
        size *= 2
    m = len(a) - w + 1
    return np.minimum(cur[:m], cur[w - size : w - size + m])


def runs(b: np.ndarray, ends: np.ndarray, window: int = WINDOW, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """Texts one after another in b, ends: their ends. (text, first window, last window, anchor, anchor's hash) of each run."""
    if len(b) < window:
        return (np.zeros(0, np.int64),) * 4 + (np.zeros(0, np.uint64),)
    h = gram_hashes(b, gram)
    least = sliding_least((h & TOP) | np.arange(len(h), dtype=np.uint64), window - gram + 1)
    anchor = (least & LOW).astype(np.int64)
    text = np.repeat(np.arange(len(ends)), np.diff(ends, prepend=0))[: len(anchor)]
    start = np.flatnonzero(np.arange(len(anchor)) + window <= ends[text])
    if not len(start):
        return (start,) * 4 + (h[:0],)
    anchor, text = anchor[start], text[start]
    new = np.flatnonzero((anchor[1:] != anchor[:-1]) | (text[1:] != text[:-1])) + 1
    first = np.concatenate([[0], new])
    last = np.concatenate([new, [len(start)]]) - 1
    return text[first], start[first], start[last], anchor[first], h[anchor[first]]


def _signed(h: int) -> int:
    return h - (1 << 63)


def text_runs(texts: list[bytes]):
    """(text, first, last, anchor, anchor hash, run hash) of the runs of each text, places in the text."""
    held: list[tuple[int, int, bytes]] = []  # text, place of the stretch, bytes
    size = 0

    def work():
        joined = b"".join(x for _, _, x in held)
        ends = np.cumsum([len(x) for _, _, x in held])
        for k, a, z, p, h in zip(*(x.tolist() for x in runs(np.frombuffer(joined, np.uint8), ends)), strict=True):
            i, place, x = held[k]
            shift = place - (int(ends[k]) - len(x))
            yield i, a + shift, z + shift, p + shift, _signed(h), _signed(xxhash.xxh3_64_intdigest(joined[a : z + WINDOW]))

    for i, raw in enumerate(texts):
        if len(raw) < WINDOW:
            continue
        for at in range(0, len(raw) - WINDOW + 1, STRETCH):
            held.append((i, at, raw[at : at + STRETCH + WINDOW - 1]))
            size += len(held[-1][2])
            if size >= GROUP:
                yield from work()
                held, size = [], 0
    if held:
        yield from work()


RUNS = "row long, first long, last long, anchor long, kh long, sp long"


def all_runs(docs: DataFrame, of=text_runs) -> DataFrame:
    def make():
        def one(part):
            ids = column(part, "row").to_pylist()
            cols = list(zip(*of(raw_texts(part)), strict=True)) or [[]] * 6
            cols[0] = [ids[i] for i in cols[0]]
            return {n: pa.array(c, pa.int64()) for n, c in zip(("row", "first", "last", "anchor", "kh", "sp"), cols, strict=True)}

        return one

    return map_slices(docs, RUNS, make)


def with_texts(docs: DataFrame, wants: DataFrame, f, schema: str) -> DataFrame:
    """f(row, text, items) -> tuples, for the documents that wants (row, ...) names; items: wants' other columns, a list each."""
    names = [c for c in wants.columns if c != "row"]
    listed = saved(wants.groupBy("row").agg(F.collect_list(F.struct(*names)).alias("items")).select("row", *(F.col(f"items.{c}").alias(c) for c in names)), "wants")
    # a table of its own, so that a join's side is read and not sorted with the texts
    joined = only_marked(docs.select("row", "text"), "row", listed.select("row")).join(listed, "row")

    def run(batches):
        for part in slices(batches, 64):
            out = []
            for row, raw, *items in zip(column(part, "row").to_pylist(), raw_texts(part), *(column(part, c).to_pylist() for c in names), strict=True):
                out += f(row, raw, list(zip(*items, strict=True)))
            yield pa.RecordBatch.from_pydict({n.split()[0]: pa.array(c) for n, c in zip(schema.split(", "), zip(*out, strict=True), strict=True)}, target(schema)) if out else pa.RecordBatch.from_pylist([], target(schema))

    return joined.mapInArrow(run, schema)


def target(schema: str) -> pa.Schema:
    kinds = {"long": pa.int64(), "int": pa.int32(), "string": pa.string(), "boolean": pa.bool_()}
    return pa.schema([(n, kinds[t]) for n, t in (x.split() for x in schema.split(", "))])


BLOCKS = "row long, first long, last long, anchor long, kh long, j long, core long, full long, n long"


def blocks(row: int, raw: bytes, items: list):
    """The blocks of 16 offsets of each run (first, last, anchor, kh, n); full: of a block that lies in the run."""
    for first, last, p, kh, n in items:
        for j in range((p - last) // BLOCK, (p - first) // BLOCK + 1):
            high = p - BLOCK * j  # the block's last window; its first is 15 before
            low = high - BLOCK + 1
            core = xxhash.xxh3_64_intdigest(raw[high : low + WINDOW])
            full = _signed(xxhash.xxh3_64_intdigest(raw[low : high + WINDOW])) if low >= first and high <= last else None
            yield row, first, last, p, kh, j, _signed(core), full, n


WINDOWS = "row long, start long, kh long, o long, wh long, n long"


def windows(row: int, raw: bytes, items: list):
    for first, last, p, kh, j, n in items:
        for start in range(max(first, p - BLOCK * j - BLOCK + 1), min(last, p - BLOCK * j) + 1):
            yield row, start, kh, p - start, _signed(xxhash.xxh3_64_intdigest(raw[start : start + WINDOW])), n


def repeated(docs: DataFrame) -> DataFrame:
    """docs (row, text) -> (row, start, n): n windows from start on are repeated ones."""
    spark = docs.sparkSession
    anchors = saved(all_runs(docs), "runs")
    spans = saved(anchors.groupBy("kh", "sp").agg(F.count("*").alias("n"), F.min(F.struct("row", "first", "last", "anchor")).alias("rep")), "spans")
    twice = saved(spans.where("n > 1").select("kh", "sp"), "twice")
    found = saved(anchors.join(twice, ["kh", "sp"]).select("row", F.col("first").alias("start"), (F.col("last") - F.col("first") + 1).alias("n")), "found")
    discard(anchors)
    release(spark)
    rivals = saved(spans.groupBy("kh").agg(F.count("*").alias("runs"), F.min("n").alias("least")).where("runs > 1 and least = 1").select("kh"), "rivals")
    wants = spans.join(rivals, "kh").select("rep.row", "rep.first", "rep.last", "rep.anchor", "kh", "n")
    level = saved(with_texts(docs, wants, blocks, BLOCKS), "blocks")
    discard(spans)
    release(spark)
    whole = saved(level.where("full is not null").groupBy("kh", "j", "full").agg(F.sum("n").alias("m")).where("m > 1").select("kh", "j", "full"), "whole")
    level = saved(level.join(whole.withColumn("covered", F.lit(True)), ["kh", "j", "full"], "left"), "level")
    from_blocks = level.where("covered and n = 1").select("row", (F.col("anchor") - F.col("j") * BLOCK - (BLOCK - 1)).alias("start"), F.lit(BLOCK).cast("long").alias("n"))
    open_ = saved(level.groupBy("kh", "j", "core").agg(F.sum("n").alias("m"), F.max((F.col("n") == 1) & F.col("covered").isNull()).alias("left")).where("m > 1 and left").select("kh", "j", "core"), "open")
    wants = level.join(open_, ["kh", "j", "core"]).select("row", "first", "last", "anchor", "kh", "j", "n")
    single = saved(with_texts(docs, wants, windows, WINDOWS), "windows")
    release(spark)
    same = saved(single.groupBy("kh", "o", "wh").agg(F.sum("n").alias("m"), F.min("n").alias("least")).where("m > 1 and least = 1").select("kh", "o", "wh"), "same")
    from_windows = single.where("n = 1").join(same, ["kh", "o", "wh"]).select("row", "start", F.lit(1).cast("long").alias("n"))
    return saved(found.unionByName(from_blocks).unionByName(from_windows), "repeated")


BLANKS = re.compile(rb"[\x20\x09-\x0D]")
BLANK = np.array([c == 32 or 9 <= c <= 13 for c in range(256)])
BYTES = mixed(np.arange(1, 257, dtype=np.uint64))
BASE = 0x9E3779B97F4A7C15


@cache
def powers(bits: int) -> tuple[np.ndarray, np.ndarray]:
    """The first 2^bits powers of BASE and of its inverse."""
    return tuple(np.cumprod(np.concatenate([[np.uint64(1)], np.full((1 << bits) - 1, x, np.uint64)])) for x in (BASE, pow(BASE, -1, 1 << 64)))


def word_hashes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words of texts one after another, and the ends of each text's words."""
    b = np.frombuffer(b" " + b" ".join(texts) + b" ", np.uint8)
    edges = np.flatnonzero(np.diff(BLANK[b]))
    first, last = edges[::2], edges[1::2]  # the byte before a word, and its last one
    up, down = powers(max(17, len(b).bit_length()))
    sums = np.cumsum(BYTES[b] * up[: len(b)])
    ends = np.cumsum([len(x) + 1 for x in texts])
    return mixed((sums[last] - sums[first]) * down[first]), np.searchsorted(first, ends)


def long_word_hashes(raw: bytes) -> np.ndarray:
    """Those of one text of any length: it is read in pieces that end at a blank; words longer than `PIECE` are hashed as a whole."""
    out, at = [np.zeros(0, np.uint64)], 0
    while at < len(raw):
        found = BLANKS.search(raw, at + PIECE)
        stop = found.start() if found else len(raw)
        word = stop if stop - at <= PIECE else 1 + max(at - 1, *(raw.rfind(c, at, stop) for c in (b" ", b"\t", b"\n", b"\v", b"\f", b"\r")))
        out.append(word_hashes([raw[at : word if stop - word > PIECE else stop]])[0])
        if stop - word > PIECE:
            out.append(mixed(np.array([xxhash.xxh3_64_intdigest(memoryview(raw)[word:stop])], np.uint64)))
        at = stop
    return np.concatenate(out)


def word_runs(texts: list[bytes], window: int):
    """As text_runs, but of words; the first digit is half a window long."""

    def work(held: list[int], w: np.ndarray, ends: np.ndarray, shift: int = 0):
        view, begin = memoryview(np.ascontiguousarray(w)).cast("B"), np.concatenate([[0], ends[:-1]])
        for k, a, z, p, h in zip(*(x.tolist() for x in runs(w, ends, window, (window + 1) // 2)), strict=True):
            to = shift - int(begin[k])
            yield held[k], a + to, z + to, p + to, _signed(h), _signed(xxhash.xxh3_64_intdigest(view[8 * a : 8 * (z + window)]))

    held, size = [], 0
    for i, raw in enumerate(texts):
        if len(raw) > PIECE:
            w = long_word_hashes(raw)
            for at in range(0, max(0, len(w) - window + 1), STRETCH):
                part = w[at : at + STRETCH + window - 1]
                yield from work([i], part, np.array([len(part)]), at)
        elif len(raw) >= 2 * window - 1:
            held.append(i)
            size += len(raw)
            if size >= GROUP:
                yield from work(held, *word_hashes([texts[k] for k in held]))
                held, size = [], 0
    if held:
        yield from work(held, *word_hashes([texts[k] for k in held]))


WORD_WINDOWS = "row long, last_row long, kh long, o long, wh long"


def passages(docs: DataFrame, words: int) -> DataFrame:
    """docs (row, text), rows distinct -> row, of those with a run of so many words that stands in another row's text, too.

    Runs of windows that two rows have settle most rows at once; single windows are compared only below the anchors of
    those that are left.
    """
    spark = docs.sparkSession
    anchors = saved(all_runs(docs, lambda texts: word_runs(texts, words)), "word_runs")
    spans = saved(anchors.groupBy("kh", "sp").agg(F.min("row").alias("row"), F.max("row").alias("last_row"), F.min(F.struct("row", "first", "last", "anchor")).alias("rep")), "word_spans")
    common = saved(spans.where("row < last_row").select("kh", "sp"), "word_common")
    sure = saved(anchors.select("row", "kh", "sp").join(common, ["kh", "sp"]).select("row").distinct(), "word_sure")
    discard(anchors)
    release(spark)
    rivals = saved(spans.groupBy("kh").agg(F.count("*").alias("n"), F.bool_or(F.col("row") == F.col("last_row")).alias("lone")).where("n > 1 and lone").select("kh"), "word_rivals")
    spans_left = saved(spans.join(rivals, "kh").select("kh", "row", "last_row", "rep.first", "rep.last", "rep.anchor"), "word_left")
    discard(spans)
    left = saved(without(spans_left.where("row = last_row"), "row", sure).select("kh").distinct(), "word_open")
    wants = spans_left.join(left, "kh")

    def windows_of(row: int, raw: bytes, items: list):
        w = long_word_hashes(raw)
        for kh, last_row, first, last, anchor in items:
            for at in range(first, last + 1):
                yield row, last_row, kh, anchor - at, _signed(xxhash.xxh3_64_intdigest(w[at : at + words].tobytes()))

    single = saved(with_texts(docs, wants.select("row", "kh", "last_row", "first", "last", "anchor"), windows_of, WORD_WINDOWS), "word_windows")
    same = single.groupBy("kh", "o", "wh").agg(F.min("row").alias("a"), F.max("last_row").alias("z")).where("a < z").select("kh", "o", "wh")
    more = single.where("row = last_row").join(same, ["kh", "o", "wh"]).select("row")
    found = saved(sure.unionByName(more).distinct(), "passages")
    release(spark)
    return found


def removed(items: list) -> list[tuple[int, int]]:
    """Maximal runs of bytes that the windows cover."""
    out: list[list[int]] = []
    for start, n in sorted(items):
        stop = start + n - 1 + WINDOW
        if out and start <= out[-1][1]:
            out[-1][1] = max(out[-1][1], stop)
        else:
            out.append([start, stop])
    return [(a, z) for a, z in out]


CUT = "row long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept string"


def cut_text(raw: bytes, spans: list[tuple[int, int]]) -> bytes:
    at, kept = 0, []
    for a, z in spans:
        kept.append(raw[at:a])
        at = z
    return b"".join(kept) + raw[at:]


def deduplicated(docs: DataFrame, texts: bool = True) -> DataFrame:
    """docs (row, text), rows distinct, not null -> row, n_bytes, n_removed, n_spans, kept_sha256, kept (the remaining text; null unless texts).

    A cut may fall inside a UTF-8 sequence: kept then has U+FFFD there, the digest is of the bytes. Only the texts that
    lose bytes are shuffled.
    """
    cover = repeated(docs)

    def cut(row, raw, items):
        spans = removed(items)
        kept = cut_text(raw, spans)
        return [(row, len(raw), len(raw) - len(kept), len(spans), hashlib.sha256(kept).hexdigest(), kept.decode("utf-8", "replace") if texts else None)]

    def make():
        return lambda part: {"row": column(part, "row")} | _uncut(raw_texts(part), texts)

    rest = without(docs.select("row", "text"), "row", cover.select("row").distinct())
    return with_texts(docs, cover, cut, CUT).unionByName(map_slices(rest, CUT, make))


def _uncut(raw: list[bytes], keep: bool) -> dict:
    n = pa.array([len(x) for x in raw], pa.int64())
    zero = pa.array([0] * len(raw), pa.int64())
    return {"n_bytes": n, "n_removed": zero, "n_spans": zero, "kept_sha256": pa.array([hashlib.sha256(x).hexdigest() for x in raw], pa.string()), "kept": pa.array([x.decode("utf-8", "replace") if keep else None for x in raw], pa.string())}


def digest(docs: DataFrame, words: int = 0) -> DataFrame:
    """docs (doc_id, text) -> doc_id, n_bytes, n_removed, n_spans, kept_sha256; with words, shares_passage: whether so many words in a row stand in another row's text."""
    n, ids = docs.agg(F.count("*"), F.count_distinct("doc_id")).first()
    names = ["n_bytes", "n_removed", "n_spans", "kept_sha256"]
    keyed = n == ids
    rows = docs.select(F.col("doc_id").cast("long").alias("row"), "text") if keyed else saved(docs.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long"), "text"), "rows")
    texts = rows.select("row", "text")
    shared = passages(texts, words) if words else None
    out = deduplicated(texts, texts=False)
    if shared is not None:
        out = out.join(shared.withColumn("shares_passage", F.lit(True)), "row", "left").withColumn("shares_passage", F.coalesce("shares_passage", F.lit(False)))
        names.append("shares_passage")
    out = out.withColumn("doc_id", F.col("row")) if keyed else out.join(rows.select("row", "doc_id"), "row")
    return out.select("doc_id", *names)
