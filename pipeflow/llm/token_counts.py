"""Token counts: rollups by source, language and tokenizer version that signed deltas maintain.

A store is a folder. Batches are numbered in the order in which they are applied, whatever their ids: `ledger/<number>`
has, for each document of a batch, what it counts for from then on; `deltas/<number>` the signed changes of the totals
that follow from it; `commits/<number>-<id>` marks the batch as taken. The delta of a document is its new count less the
count that it has by the last batch that named it, so inserts, revisions and deletes are one case, and a total is the sum
of its deltas. A number's folders are overwritten until its batch is committed and left alone afterwards: handing a batch
in again, after a failure or by mistake, changes nothing.

Changes are (doc_id, text, source, lang, deleted). A document has one count for each tokenizer version under which it was
handed in; a delete ends them all, whatever version it comes with. Null texts count 0 tokens; null source and lang are
keys of their own. Null ids can't be found again and are taken as inserts of their own. Of rows that repeat an id in one
batch, the last by (deleted, text) counts, deletes first of all. Other columns are not read.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pipeflow.llm.common import column, discard, fresh_path, map_slices, saved
from pipeflow.llm.tokens import encoder

KEYS = ["source", "lang", "tokenizer"]
LEDGER = "doc_id long, tokenizer string, source string, lang string, tokens long, present boolean, seq long"
DELTAS = "source string, lang string, tokenizer string, documents long, tokens long"
COUNTED = "doc_id long, source string, lang string, deleted boolean, digest long, tokens long"


def counted(changes: DataFrame, vocabulary: str) -> DataFrame:
    """Each change with the number of its text's tokens."""

    def make():
        enc = encoder(vocabulary)

        def one(part):
            n = [len(x) // 4 for x in enc.ids([t or "" for t in column(part, "text").to_pylist()])]
            return {c: column(part, c) for c in ("doc_id", "source", "lang", "deleted", "digest")} | {"tokens": pa.array(n, pa.int64())}

        return one

    rows = changes.select(F.col("doc_id").cast("long"), "text", "source", "lang", F.coalesce("deleted", F.lit(False)).alias("deleted"), F.xxhash64("text").alias("digest"))
    return map_slices(rows, COUNTED, make)


class Rollup:
    """One store. Batches are applied one after another; a reader sees committed batches only."""

    def __init__(self, spark: SparkSession, folder: str | None = None):
        self.spark, self.folder = spark, folder or fresh_path(spark, "counts")

    def _path(self, *parts: object) -> str:
        return "/".join([self.folder, *map(str, parts)])

    def _fs(self, path: str):
        p = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        return p.getFileSystem(self.spark._jsc.hadoopConfiguration()), p

    def committed(self) -> list[tuple[int, int]]:
        """(number, batch) of the batches that were taken, in order."""
        fs, p = self._fs(self._path("commits"))
        names = [s.getPath().getName() for s in fs.listStatus(p)] if fs.exists(p) else []
        return sorted((int(number), int(batch)) for number, _, batch in (x.partition("-") for x in names))

    def _read(self, kind: str, schema: str) -> DataFrame:
        out = self.spark.createDataFrame([], schema)
        done = self.committed()
        return self.spark.read.schema(schema).parquet(*(self._path(kind, str(n)) for n, _ in done)) if done else out

    def _held(self, ids: DataFrame) -> DataFrame:
        """What documents of ids (doc_id, deleted) count for until now: a row for each tokenizer version."""
        ledger = self._read("ledger", LEDGER).join(ids, "doc_id")
        last = ledger.where("present").groupBy("doc_id", "deleted", "tokenizer").agg(F.max(F.struct("seq", "tokens", "source", "lang")).alias("o"))
        ended = ledger.where("not present").groupBy("doc_id").agg(F.max("seq").alias("ended"))
        return last.join(ended, "doc_id", "left").where("ended is null or ended < o.seq").select("deleted", "tokenizer", "o.tokens", "o.source", "o.lang")

    def apply(self, batch: int, changes: DataFrame, vocabulary: str, tokenizer: str) -> bool:
        """Takes in a batch of changes counted by a tokenizer version; False if it was taken before. Texts are tokenised once."""
        done = self.committed()
        if batch in (b for _, b in done):
            return False
        number = done[-1][0] + 1 if done else 1
        order = F.struct(~F.col("deleted"), "digest", "tokens", F.coalesce("source", F.lit("")), F.coalesce("lang", F.lit("")), "source", "lang")
        rows = saved(counted(changes, vocabulary), "counted")
        known = rows.where("doc_id is not null").groupBy("doc_id").agg(F.max(order).alias("c"))
        fresh = rows.where("doc_id is null and not deleted").select("doc_id", "source", "lang", "tokens", F.lit(True).alias("present"))
        new = known.select("doc_id", "c.source", "c.lang", "c.tokens", F.col(f"c.{known.schema['c'].dataType.names[0]}").alias("present")).unionByName(fresh)
        new = new.select("doc_id", F.lit(tokenizer).alias("tokenizer"), "source", "lang", "tokens", "present", F.lit(number).cast("long").alias("seq"))
        ledger = self._path("ledger", str(number))
        new.write.mode("overwrite").parquet(ledger)
        discard(rows)
        new = self.spark.read.schema(LEDGER).parquet(ledger)
        deltas = new.where("present").select(*KEYS, F.lit(1).cast("long").alias("documents"), "tokens")
        if done:
            old = self._held(new.where("doc_id is not null").select("doc_id", (~F.col("present")).alias("deleted"))).where(F.col("deleted") | (F.col("tokenizer") == tokenizer))
            deltas = deltas.unionByName(old.select(*KEYS, F.lit(-1).cast("long").alias("documents"), (-F.col("tokens")).alias("tokens")))
        summed = deltas.groupBy(*KEYS).agg(F.sum("documents").alias("documents"), F.sum("tokens").alias("tokens"))
        summed.coalesce(1).write.mode("overwrite").parquet(self._path("deltas", str(number)))
        fs, p = self._fs(self._path("commits", f"{number}-{batch}"))
        fs.create(p, True).close()
        return True

    def totals(self) -> DataFrame:
        """source, lang, tokenizer, documents, tokens; keys that no document is left of are gone."""
        out = self._read("deltas", DELTAS).groupBy(*KEYS).agg(F.sum("documents").alias("documents"), F.sum("tokens").alias("tokens"))
        return out.where("documents != 0 or tokens != 0").select(*KEYS, "documents", "tokens")
