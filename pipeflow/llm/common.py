"""What the operators share: shared-folder tables, Arrow mapping in small slices, word hashes."""

from __future__ import annotations

import contextlib
import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows that a Python operator holds as Python objects at a time; rows of an Arrow batch.
SLICE, BATCH = 256, 512
#: Bits of a bitmap for each marked id, and of the largest bitmap that is broadcast (16 MB).
BITS_EACH, MOST_BITS = 16, 1 << 27

LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Only a local session gets a folder of its own where it is unset."""
    at = spark.conf.get("spark.checkpoint.dir", None)
    if not at:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        at = f"file://{tempfile.mkdtemp(prefix='pipeflow-')}"
        spark.conf.set("spark.checkpoint.dir", at)
    return at.rstrip("/")


def _delete_later(spark: SparkSession, path: str) -> None:
    jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
    jpath.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(jpath)


def fresh_path(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder, removed when the session's JVM ends."""
    path = f"{shared_dir(spark)}/pipeflow/{name}-{uuid.uuid4().hex}"
    _delete_later(spark, path)
    return path


def saved(df: DataFrame, name: str) -> DataFrame:
    """df written once as Parquet to the shared folder and read again: cuts the lineage and survives lost executors."""
    path = fresh_path(df.sparkSession, name)
    df.write.option("compression", "zstd").parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.pipeflow_path = path
    return out


def discard(df: DataFrame) -> None:
    """Removes a table made by saved() that nothing reads any more."""
    spark = df.sparkSession
    jpath = spark._jvm.org.apache.hadoop.fs.Path(df.pipeflow_path)
    jpath.getFileSystem(spark._jsc.hadoopConfiguration()).delete(jpath, True)


def release(spark: SparkSession) -> None:
    """Lets Spark drop shuffle files of finished jobs: it does so when the driver's JVM collects garbage."""
    import gc

    gc.collect()
    spark._jvm.System.gc()


def unused(df: DataFrame, name: str) -> str:
    """A column name that df doesn't have, whatever the case of its names."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def ids_are_keys(docs: DataFrame) -> bool:
    """Whether every doc_id is there and none repeats."""
    n, ids = docs.agg(F.count("*"), F.count_distinct(F.col("doc_id").cast("long"))).first()
    return n == ids


def small_batches(spark: SparkSession) -> None:
    """At most `BATCH` rows in an Arrow batch: texts and sets may be long, and the JVM and Python both hold a batch."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= BATCH:
        spark.conf.set(key, str(BATCH))


_resident: dict[object, object] = {}


def resident(key: object = None, make: Callable[[], object] | None = None) -> object:
    """What a Python worker keeps from task to task, one thing at a time: a worker that turns to other work gives up what it held before."""
    if key in _resident:
        return _resident[key]
    if _resident:
        _resident.clear()
        with contextlib.suppress(OSError, AttributeError):  # the C library gives freed memory back, where it can
            ctypes.CDLL(None).malloc_trim(0)
    return _resident.setdefault(key, make()) if make else None


def slices(batches: Iterator[pa.RecordBatch], size: int = SLICE) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, size):
            yield batch.slice(at, size)


def map_slices(df: DataFrame, schema: str, make: Callable[[], Callable[[pa.RecordBatch], pa.RecordBatch | dict]], only: tuple[str, np.ndarray] | None = None) -> DataFrame:
    """mapInArrow with one call of make() per task and its function called on slices of a few hundred rows.

    only: a column of ids and a bitmap; rows whose id isn't marked are skipped, in the same worker.
    """
    sent = df.sparkSession.sparkContext.broadcast(only[1]) if only else None

    def run(batches):
        f = make()
        for part in slices(batches):
            if only:
                part = part.filter(pa.array(is_marked(column(part, only[0]).to_numpy(zero_copy_only=False), sent.value)))
            out = f(part)
            yield out if isinstance(out, pa.RecordBatch) else pa.RecordBatch.from_pydict(out)

    small_batches(df.sparkSession)
    return df.mapInArrow(run, schema)


def raw_texts(part: pa.RecordBatch, name: str = "text") -> list[bytes]:
    """The texts as UTF-8 bytes, null as empty."""
    column = part.column(part.schema.get_field_index(name))
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def column(part: pa.RecordBatch, name: str) -> pa.Array:
    return part.column(part.schema.get_field_index(name))


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))


MIX1, MIX2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def mixed(h: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values."""
    h = (h ^ (h >> np.uint64(30))) * MIX1
    h = (h ^ (h >> np.uint64(27))) * MIX2
    return h ^ (h >> np.uint64(31))


def shingle_hashes(h: np.ndarray, k: int) -> np.ndarray:
    """Hashes of the k-word windows of a sequence of word hashes; of the whole sequence if it is shorter."""
    n = len(h)
    if not n:
        return h
    k = min(k, n)
    out = mixed(h[: n - k + 1] + np.uint64(k))
    for i in range(1, k):
        out = mixed(out * np.uint64(0x9E3779B97F4A7C15) + h[i : n - k + 1 + i])
    return out


def remainder(doc_id: Column, by: int) -> Column:
    """crc32 of the id's decimal text, modulo by: the fold of a labelled row. Null ids are in fold 0 of their own."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % by, F.lit(0))


def bounded(df: DataFrame, n: int, *cols: str) -> DataFrame:
    """The n rows whose hash of doc_id is least: the same for every order of the input; cols stay."""
    return df.orderBy(F.xxhash64("doc_id"), "doc_id").limit(n).select(*cols)


def marked_bits(ids: DataFrame) -> np.ndarray | None:
    """A bitmap of the ids' hashes: what a scan may skip is what isn't marked. None if it would be too large to send round.

    An unmarked id is surely not among ids; a marked one may be. Its length follows from a count of the ids, so that few
    others are marked by chance. Each task sends at most bits / 64 words.
    """
    name = ids.columns[0]
    ids = ids.where(F.col(name).isNotNull()).select(name)
    bits = 1 << max(16, (BITS_EACH * ids.count()).bit_length())
    if bits > MOST_BITS:
        return None

    def collect(batches):
        seen = np.zeros(bits, bool)
        for batch in batches:
            if batch.num_rows:
                seen[slot(batch.column(0).to_numpy(), bits)] = True
        words = np.packbits(seen, bitorder="little").view("<i8")
        at = np.flatnonzero(words)
        yield pa.RecordBatch.from_pydict({"word": pa.array(at.astype(np.int32)), "value": pa.array(words[at])})

    table = ids.mapInArrow(collect, "word int, value long").groupBy("word").agg(F.bit_or("value").alias("value")).toArrow()
    out = np.zeros(bits // 64, "<i8")
    out[table.column("word").to_numpy()] = table.column("value").to_numpy()
    return out


def slot(ids: np.ndarray, bits: int) -> np.ndarray:
    return (mixed(ids.astype(np.int64).view(np.uint64)) % np.uint64(bits)).astype(np.int64)


def is_marked(ids: np.ndarray, words: np.ndarray) -> np.ndarray:
    at = slot(ids, 64 * len(words))
    return (words[at >> 6].view(np.uint64) >> (at & 63).astype(np.uint64)) & np.uint64(1) > 0


def filtered(df: DataFrame, name: str, words: np.ndarray, marked: bool) -> DataFrame:
    """Rows of df whose id is (or isn't) marked; rows without an id are never marked. Runs beside the scan: no shuffle."""
    shared = df.sparkSession.sparkContext.broadcast(words)

    def run(batches):
        for part in slices(batches):
            ids = column(part, name)
            mask = is_marked(ids.fill_null(0).to_numpy(zero_copy_only=False), shared.value) & ids.is_valid().to_numpy(zero_copy_only=False)
            mask = mask if marked else ~mask
            if mask.any():
                yield part if mask.all() else part.filter(pa.array(mask))

    small_batches(df.sparkSession)
    return df.mapInArrow(run, df.schema)


def only_marked(df: DataFrame, name: str, ids: DataFrame) -> DataFrame:
    """df's rows whose id is in ids (one column), and perhaps a few more. Without a shuffle of df while ids are few enough for a bitmap; else by a join."""
    words = marked_bits(ids)
    if words is None:
        return df.join(ids.select(F.col(ids.columns[0]).alias(name)).distinct(), name, "left_semi").select(*df.columns)
    return filtered(df, name, words, True)


def without(df: DataFrame, name: str, ids: DataFrame) -> DataFrame:
    """df's rows whose id isn't in ids (one column). Only rows that may be are shuffled while ids are few enough for a bitmap."""
    gone = ids.select(F.col(ids.columns[0]).alias(name)).distinct()
    words = marked_bits(ids)
    if words is None:
        return df.join(gone, name, "left_anti").select(*df.columns)
    return filtered(df, name, words, False).unionByName(filtered(df, name, words, True).join(gone, name, "left_anti").select(*df.columns))
