"""Token ids in binary files: independent zstandard frames, a seek table behind them, a checksum for each frame.

A file is a row of zstandard frames of whole documents' ids (little-endian unsigned 32 bit), a skippable frame with the
index of documents (ids, first frame, place, length) and a skippable frame with the seek table of the public seekable
format: compressed size, plain size and the low 32 bits of the frame's XXH64, then the number of frames. A reader gets
the tail, finds the frames of the documents it wants and decompresses only those.

Texts are tokenised where they are scanned; only packed ids are shuffled, two bytes an id where the vocabulary allows.

Null texts are empty and hold the end id alone. Null doc_ids come first, rows of one doc_id follow each other by the
checksum of their ids, so that a range holds a stretch of a hot id (or of null ids) and not all of it. Tasks write under a name of their own attempt and only files named by tasks that ended well are listed, so a lost
executor leaves nothing behind in the list.
"""

from __future__ import annotations

import os
import struct
import uuid
import zlib
from collections.abc import Iterable

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pipeflow.llm.common import column, discard, fresh_path, map_slices, saved, slices
from pipeflow.llm.tokens import encoder

SKIP_INDEX, SKIP_TABLE, SEEKABLE = 0x184D2A50, 0x184D2A5E, 0x8F92EAB1
END_ID = 1
FRAME_BYTES = 1 << 18
NO_ID = -(1 << 63)

MANIFEST = "file string, n_docs long, n_tokens long, part int"
DOC = np.dtype([("doc_id", "<i8"), ("frame", "<u4"), ("at", "<u4"), ("length", "<u4"), ("has_id", "<u4")])


def filesystem(uri: str):
    """Any store that pyarrow knows by its URI; a bare path is local."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri if "://" in uri else f"file://{os.path.abspath(uri)}")


class FrameWriter:
    """Writes documents of packed ids to an open binary stream."""

    def __init__(self, out, frame_bytes: int = FRAME_BYTES, level: int = 1):
        import zstandard

        self.out, self.most, self.zip = out, frame_bytes, zstandard.ZstdCompressor(level=level, write_checksum=True, write_content_size=True)
        self.held: list[bytes] = []
        self.size, self.frames, self.docs = 0, [], []

    def add(self, doc_id: int | None, packed: bytes) -> None:
        self.docs.append((NO_ID if doc_id is None else doc_id, len(self.frames), self.size // 4, len(packed) // 4, doc_id is not None))
        self.held.append(packed)
        self.size += len(packed)
        if self.size >= self.most:
            self._flush()

    def _flush(self) -> None:
        raw = b"".join(self.held)
        frame = self.zip.compress(raw)
        self.out.write(frame)
        self.frames.append((len(frame), len(raw), xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF))
        self.held, self.size = [], 0

    def close(self) -> None:
        if self.held:
            self._flush()
        index = zlib.compress(np.array(self.docs, DOC).tobytes(), 1)
        self.out.write(struct.pack("<IIQ", SKIP_INDEX, len(index) + 8, len(self.docs)) + index)
        table = b"".join(struct.pack("<III", *x) for x in self.frames)
        self.out.write(struct.pack("<II", SKIP_TABLE, len(table) + 17) + table + struct.pack("<QIBI", len(index) + 16, len(self.frames), 0x80, SEEKABLE))


class FrameReader:
    """Random access to a file of FrameWriter: reads the tail, then only the frames that are asked for."""

    def __init__(self, source):
        self.source = source
        n = source.size()
        index_bytes, n_frames, flags, magic = struct.unpack("<QIBI", self._read(n - 17, 17))
        if magic != SEEKABLE or not flags & 0x80:
            raise ValueError("no seek table at the end of the file")
        start = n - 17 - 12 * n_frames
        self.table = np.frombuffer(self._read(start, 12 * n_frames), "<u4").reshape(-1, 3)
        self.starts = np.concatenate([[0], np.cumsum(self.table[:, 0], dtype=np.int64)])
        block = self._read(start - 8 - index_bytes, index_bytes)
        self.docs = np.frombuffer(zlib.decompress(block[16:]), DOC)

    def _read(self, at: int, n: int) -> bytes:
        self.source.seek(at)
        return self.source.read(n)

    def frame(self, k: int) -> bytes:
        import zstandard

        size, plain, check = (int(x) for x in self.table[k])
        raw = zstandard.ZstdDecompressor().decompress(self._read(int(self.starts[k]), size), max_output_size=plain)
        if xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF != check:
            raise ValueError(f"frame {k} doesn't match its checksum")
        return raw

    def packed(self, rows: Iterable[int]):
        """(row, packed ids) of the documents in these rows of the index, each frame read once."""
        have, raw = -1, b""
        for r in rows:
            d = self.docs[r]
            if d["frame"] != have:
                have, raw = int(d["frame"]), self.frame(int(d["frame"]))
            yield r, raw[4 * int(d["at"]) : 4 * (int(d["at"]) + int(d["length"]))]


def tokenised(docs: DataFrame, vocabulary: str) -> DataFrame:
    """docs (doc_id, text) -> doc_id, wide (four bytes an id, else two), ids with the end id, their crc32."""

    def make():
        enc = encoder(vocabulary)
        wide = len(enc.ends) > 1 << 16
        end = struct.pack("<I", END_ID)

        def one(part):
            packed = [x + end for x in enc.ids([x or "" for x in column(part, "text").to_pylist()])]
            crc = pa.array(map(zlib.crc32, packed), pa.int64())
            ids = packed if wide else [np.frombuffer(x, "<u4").astype("<u2").tobytes() for x in packed]
            return {"doc_id": column(part, "doc_id"), "wide": pa.array([wide] * len(ids), pa.bool_()), "crc": crc, "ids": pa.array(ids, pa.binary())}

        return one

    return map_slices(docs.select(F.col("doc_id").cast("long"), "text"), "doc_id long, wide boolean, crc long, ids binary", make)


def write(docs: DataFrame, folder: str, vocabulary: str) -> DataFrame:
    """Files of docs (doc_id, text) in ascending doc_id order across `folder`; returns the manifest, in file order."""
    spark = docs.sparkSession
    n_files = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    # a table, so that neither the sampling of the ranges nor a lost executor tokenises a text again
    packed = saved(tokenised(docs, vocabulary), "ids")
    keys = [F.col("doc_id").asc_nulls_first(), F.col("crc"), F.col("row")]
    ranged = packed.withColumn("row", F.monotonically_increasing_id()).repartitionByRange(n_files, *keys)
    ordered = ranged.sortWithinPartitions(*keys).select("doc_id", "wide", "ids", F.spark_partition_id().alias("part"))

    def put(batches):
        store, root = filesystem(folder)
        store.create_dir(root, recursive=True)
        writer = out = None
        name, part_id, n_tokens = "", 0, 0
        for part in slices(batches):
            if not part.num_rows:
                continue
            if writer is None:
                part_id = column(part, "part")[0].as_py()
                name = f"ids-{part_id:06d}-{uuid.uuid4().hex}.zst"
                out = store.open_output_stream(f"{root}/{name}", compression=None)
                writer = FrameWriter(out)
            for doc_id, wide, raw in zip(column(part, "doc_id").to_pylist(), column(part, "wide").to_pylist(), column(part, "ids").to_pylist(), strict=True):
                plain = raw if wide else np.frombuffer(raw, "<u2").astype("<u4").tobytes()
                writer.add(doc_id, plain)
                n_tokens += len(plain) // 4
        if writer is not None:
            writer.close()
            out.close()
            yield pa.RecordBatch.from_pydict({"file": [name], "n_docs": pa.array([len(writer.docs)], pa.int64()), "n_tokens": pa.array([n_tokens], pa.int64()), "part": pa.array([part_id], pa.int32())})

    rows = sorted(ordered.mapInArrow(put, MANIFEST).collect(), key=lambda r: r.part)
    discard(packed)
    return spark.createDataFrame(rows, MANIFEST)


def read(spark: SparkSession, folder: str, manifest: DataFrame) -> DataFrame:
    """Each document of the files: doc_id, start, n_tokens, ids_crc32 and ids, from the frames. One task a file."""
    rows = manifest.orderBy("part").collect()  # a row a file
    base = np.concatenate([[0], np.cumsum([r.n_tokens for r in rows])]).tolist()
    listed = spark.createDataFrame([(r.file, b) for r, b in zip(rows, base, strict=False)], "file string, base long")

    def get(batches):
        store, root = filesystem(folder)
        for batch in batches:
            for file, start in zip(*(column(batch, c).to_pylist() for c in ("file", "base")), strict=True):
                with store.open_input_file(f"{root}/{file}") as source:
                    reader = FrameReader(source)
                    docs = reader.docs
                    places = start + np.concatenate([[0], np.cumsum(docs["length"], dtype=np.int64)])
                    out: dict[str, list] = {k: [] for k in ("doc_id", "start", "n_tokens", "ids_crc32", "ids")}
                    for r, raw in reader.packed(range(len(docs))):
                        d = docs[r]
                        for k, v in zip(out, (int(d["doc_id"]) if d["has_id"] else None, int(places[r]), len(raw) // 4, zlib.crc32(raw), raw), strict=True):
                            out[k].append(v)
                        if len(out["doc_id"]) >= 1024:
                            yield _rows(out)
                            out = {k: [] for k in out}
                    if out["doc_id"]:
                        yield _rows(out)

    return listed.repartition(max(len(rows), 1), "file").mapInArrow(get, "doc_id long, start long, n_tokens long, ids_crc32 long, ids binary")


def _rows(out: dict) -> pa.RecordBatch:
    return pa.RecordBatch.from_pydict({k: pa.array(v, pa.binary() if k == "ids" else pa.int64()) for k, v in out.items()})


def write_and_read(docs: DataFrame, vocabulary: str) -> DataFrame:
    folder = fresh_path(docs.sparkSession, "ids")
    return read(docs.sparkSession, folder, write(docs, folder, vocabulary)).drop("ids")
