"""Exact deduplication with Patricia-trie owners.

Texts are normalised (A-Z to lower case, null as empty). Each task first puts its own rows in a trie and passes on one
row a distinct text, so a text that a third of all rows share arrives as one row a task. Those texts are dealt by
length and content hash; in each partition a compressed radix trie over the full bytes owns them: its terminal nodes
hold the best identifier and the number of rows. A trie beyond its memory spills its largest subtree to a local file
of its own task (scratch that nobody else reads; a lost task is computed again) and works it off, subtree by subtree,
at the end. Rows find their owner through their task's representative.

The row with the largest (or smallest) doc_id stays; a null id loses to any other and, if all are null, is the keep id.
Of rows that repeat an id, `kept` holds for each row with the id that stays. Other columns are not read.
"""

from __future__ import annotations

import hashlib
import pickle
import tempfile
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pipeflow.llm.common import LOWER, column, discard, ids_are_keys, raw_texts, resident, saved, slices, small_batches, unused, without


def better(a: int | None, b: int | None, largest: bool) -> int | None:
    if a is None or b is None:
        return b if a is None else a
    return max(a, b) if largest else min(a, b)


#: Bytes that a tag is booked with: a pair of numbers, the numbers, and its place in the list.
TAG = 150


class Node:
    __slots__ = ("label", "children", "entry")

    def __init__(self, label: bytes, entry=None):
        self.label, self.children, self.entry = label, {}, entry


def common(a: bytes, b: bytes, at: int) -> int:
    """Bytes that label a shares with b from b[at] on."""
    n = min(len(a), len(b) - at)
    if a[:n] == b[at : at + n]:
        return n
    low, high = 0, n  # a[:low] agrees, a[:high] doesn't
    while high - low > 1:
        mid = (low + high) // 2
        if a[low:mid] == b[at + low : at + mid]:
            low = mid
        else:
            high = mid
    return low


class OwnerTrie:
    """A radix trie of whole byte strings. entry: [best id, rows, tags of the rows that asked]; spills by subtree."""

    def __init__(self, largest: bool, budget: int = 64 << 20, depth: int = 0):
        self.largest, self.budget, self.depth = largest, budget, depth
        self.root, self.held = Node(b""), 0
        self.spilled: dict[int, object] = {}  # first byte -> file of (text, best, n, tags)

    def insert(self, text: bytes, best: int | None, n: int, tags: list) -> None:
        if text and text[0] in self.spilled:
            pickle.dump((text, best, n, tags), self.spilled[text[0]], -1)
            return
        node, at = self.root, 0
        while at < len(text):
            child = node.children.get(text[at])
            if child is None:
                fresh = node.children[text[at]] = Node(text[at:])
                self.held += len(text) - at + 200
                node, at = fresh, len(text)
                break
            k = common(child.label, text, at)
            if k < len(child.label):
                top = Node(child.label[:k])
                child.label = child.label[k:]
                top.children[child.label[0]] = child
                node.children[text[at]] = top
                child = top
                self.held += 200
            node, at = child, at + k
        entry = node.entry
        if entry is None:
            node.entry = [best, n, list(tags)]
        else:
            entry[0], entry[1] = better(entry[0], best, self.largest), entry[1] + n
            entry[2] += tags
        self.held += TAG * len(tags)
        if self.held > self.budget:
            self._spill()

    def _spill(self) -> None:
        if not self.root.children:
            return
        first = max(self.root.children, key=lambda c: self._size(self.root.children[c]))
        node = self.root.children.pop(first)
        self.held -= self._size(node)
        file = self.spilled[first] = tempfile.TemporaryFile()
        for text, entry in self._walk(node, b""):
            pickle.dump((text, *entry), file, -1)

    def _size(self, top: Node) -> int:
        total, todo = 0, [top]
        while todo:
            x = todo.pop()
            total += len(x.label) + 200 + (TAG * len(x.entry[2]) if x.entry else 0)
            todo += x.children.values()
        return total

    def _walk(self, top: Node, prefix: bytes) -> Iterator[tuple[bytes, list]]:
        todo = [(top, prefix)]
        while todo:
            x, before = todo.pop()
            text = before + x.label
            if x.entry:
                yield text, x.entry
            todo += [(c, text) for c in x.children.values()]

    def owners(self) -> Iterator[tuple[bytes, int | None, int, list]]:
        """Every text once: text, best id, rows, tags. Ends the trie."""
        for text, entry in self._walk(self.root, b""):
            yield (text, *entry)
        self.root, self.held = Node(b""), 0
        for file in self.spilled.values():
            shared = None
            for text, *_ in _stored(file):
                shared = text if shared is None else shared[: common(shared, text, 0)]
            below = OwnerTrie(self.largest, self.budget, self.depth + 1)
            # what all its texts share is taken off, so that the subtree splits where they part
            for text, best, n, tags in _stored(file):
                below.insert(text[len(shared) :], best, n, tags)
            file.close()
            for text, best, n, tags in below.owners():
                yield shared + text, best, n, tags


def _stored(file) -> Iterator[tuple]:
    file.seek(0)
    while True:
        try:
            yield pickle.load(file)
        except EOFError:
            return


LOCAL = "doc_id long, row long, rep long, sha string, text binary, len int, hash long, best long, n long"


def _local(largest: bool, room: int):
    """Rows with their task's representative; the representative's row comes with its text when a trie is worked off."""

    def run(batches):
        resident()
        base, serial = None, 0
        trie = OwnerTrie(largest, 1 << 60)
        for part in slices(batches):
            if not part.num_rows:
                continue
            if base is None:
                base = column(part, "_part")[0].as_py() << 40
            for doc_id, row, raw in zip(column(part, "doc_id").to_pylist(), column(part, "row").to_pylist(), raw_texts(part), strict=True):
                text = raw.translate(LOWER)
                trie.insert(text, doc_id, 1, [(doc_id, row)])
            if trie.held > room:
                yield from _flush(trie, base, serial)
                serial += 1 << 24
                trie = OwnerTrie(largest, 1 << 60)
        if base is not None:
            yield from _flush(trie, base, serial)

    return run


def _flush(trie: OwnerTrie, base: int, serial: int) -> Iterator[pa.RecordBatch]:
    cols: list[list] = [[] for _ in range(9)]
    held = 0
    for text, best, n, rows in trie.owners():
        rep = base + serial
        serial += 1
        first, sha, h = True, hashlib.sha256(text).hexdigest(), xxhash.xxh3_64_intdigest(text) - (1 << 63)
        held += len(text)
        for doc_id, row in rows:
            for c, v in zip(cols, (doc_id, row, rep, sha, text, len(text), h, best, n) if first else (doc_id, row, rep, sha, None, None, None, None, None), strict=True):
                c.append(v)
            first = False
            held += TAG
            if held > 4 << 20:
                yield _batch(cols)
                cols, held = [[] for _ in range(9)], 0
    if cols[0]:
        yield _batch(cols)


def _batch(cols: list[list]) -> pa.RecordBatch:
    types = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=[x.split()[0] for x in LOCAL.split(", ")])


def _own(largest: bool, budget: int):
    def run(batches):
        trie = OwnerTrie(largest, budget)
        for part in slices(batches):
            for text, rep, best, n in zip(*(column(part, c).to_pylist() for c in ("text", "rep", "best", "n")), strict=True):
                trie.insert(text, best, n, [rep])
        cols: list[list] = [[], [], []]
        for _, best, n, reps in trie.owners():
            for rep in reps:
                for c, v in zip(cols, (rep, best, n), strict=True):
                    c.append(v)
            if len(cols[0]) > 50_000:
                yield pa.RecordBatch.from_pydict({k: pa.array(c, pa.int64()) for k, c in zip(("rep", "keep_id", "group_size"), cols, strict=True)})
                cols = [[], [], []]
        yield pa.RecordBatch.from_pydict({k: pa.array(c, pa.int64()) for k, c in zip(("rep", "keep_id", "group_size"), cols, strict=True)})

    return run


def groups(docs: DataFrame, keep: str = "smallest", room: int = 48 << 20, budget: int = 64 << 20) -> DataFrame:
    """docs (doc_id, text) -> a row a document: doc_id, keep_id, group_size, kept, text_sha256."""
    out, _ = _groups(docs.select("doc_id", "text", F.lit(None).cast("long").alias("row")), keep, room, budget)
    return out.select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def _groups(docs: DataFrame, keep: str, room: int = 48 << 20, budget: int = 64 << 20) -> tuple[DataFrame, DataFrame]:
    """The groups, and the saved table that they are read from."""
    largest = keep == "largest"
    small_batches(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long"), "row", "text").withColumn("_part", F.spark_partition_id().cast("long"))
    local = saved(rows.mapInArrow(_local(largest, room), LOCAL), "exact")
    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    texts = local.where("text is not null").select("text", "rep", "best", "n", "len", "hash").repartition(n, "len", "hash")
    owners = texts.mapInArrow(_own(largest, budget), "rep long, keep_id long, group_size long")
    out = local.select("doc_id", "row", "rep", "sha").join(owners, "rep")
    return out.select("doc_id", "row", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.col("sha").alias("text_sha256")), local


def deduplicated(docs: DataFrame, keep: str = "smallest") -> DataFrame:
    """docs with one row of each group of equal texts, all columns; of rows with one id and text, the first stays.

    Rows are told apart by doc_id where that is a key, else by a number in a table of their own. Only rows that may go
    are shuffled at the end.
    """
    row = unused(docs, "row")
    if ids_are_keys(docs):
        kept = docs.withColumn(row, F.col("doc_id").cast("long"))
    else:
        kept = saved(docs.withColumn(row, F.monotonically_increasing_id()), "exact-rows")
    found, local = _groups(kept.select("doc_id", "text", F.col(row).alias("row")), keep)
    marked = saved(found, "exact-groups")
    discard(local)
    best = marked.where("kept").groupBy("keep_id", "text_sha256").agg(F.min("row").alias("row")).select("row")
    gone = saved(marked.select("row").join(best, "row", "left_anti"), "exact-gone")
    discard(marked)
    return without(kept, row, gone).select(*docs.columns)


ORACLE = r"""
WITH norm AS (
  SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS t FROM documents),
grouped AS (SELECT t, max(doc_id) AS keep_id, count(*) AS group_size FROM norm GROUP BY t)
SELECT n.doc_id, g.keep_id, CAST(g.group_size AS BIGINT) AS group_size, n.doc_id IS NOT DISTINCT FROM g.keep_id AS kept, sha256(n.t) AS text_sha256
FROM norm n JOIN grouped g ON n.t = g.t
"""
