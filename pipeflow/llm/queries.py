"""The registered queries of the training-data operators, with production parameters over whole tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pipeflow.llm import exact_dedup, mixing, near_dedup, packing, quality_classifier, quality_rules, suffix_dedup, token_counts, token_output, toxicity
from pipeflow.llm.common import documents, labels, only_marked, remainder
from pipeflow.llm.tokens import vocabulary

TOKENIZER = "word_bpe_49k.json"


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = quality_rules.fit(docs, labels(spark, sf_dir).where("quality = 1"))
    return quality_rules.apply(docs, model)


def op2_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(documents(spark, sf_dir), vocabulary(TOKENIZER))


def op3_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.digest(documents(spark, sf_dir))


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole table as a batch of inserts, handed in twice; documents labelled 0 for quality revised, their digits masked; those labelled toxic deleted; then the totals."""
    docs, marks = documents(spark, sf_dir), labels(spark, sf_dir)
    changes = docs.select("doc_id", "text", "source", "lang", F.lit(False).alias("deleted"))
    poor = marks.where("quality = 0 and doc_id is not null").select("doc_id").distinct()
    revised = only_marked(changes, "doc_id", poor).join(poor, "doc_id", "left_semi").withColumn("text", F.regexp_replace("text", "[0-9]+", "0"))
    toxic = marks.where("toxic = 1").select("doc_id", *(F.lit(None).cast("string").alias(c) for c in ("text", "source", "lang")), F.lit(True).alias("deleted"))
    store = token_counts.Rollup(spark)
    for batch, rows in ((1, changes), (1, changes), (2, revised), (3, toxic)):
        store.apply(batch, rows, vocabulary(TOKENIZER), "word_bpe_49k")
    return store.totals()


def _held_out(doc_id: Column, by: int, at: int) -> Column:
    return (remainder(doc_id, by) == at).alias("held_out")


def op5_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    trusted = labels(spark, sf_dir).where(remainder(F.col("doc_id"), 3) != 1).where("quality = 1")
    scored = quality_classifier.score(docs, quality_classifier.fit(docs, trusted))
    return scored.select("doc_id", _held_out(F.col("doc_id"), 3, 1), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op6_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.components_of(documents(spark, sf_dir).select("doc_id", "text"), k=2)


def _toxicity_network(spark: SparkSession, docs: DataFrame, sf_dir: str) -> toxicity.Network:
    return toxicity.fit(docs, labels(spark, sf_dir).where(remainder(F.col("doc_id"), 4) != 2))


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    scored = toxicity.score(docs, _toxicity_network(spark, docs, sf_dir))
    return scored.select("doc_id", _held_out(F.col("doc_id"), 4, 2), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op8_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Repeats of 400 bytes and more are cut; passages of over 50 words that other documents have, too, are marked whatever their bytes."""
    cut = suffix_dedup.digest(documents(spark, sf_dir).select("doc_id", "text"), words=51)
    return cut.select(*(c for c in cut.columns if c != "shares_passage"), (F.col("n_removed") > 0).alias("touched"), "shares_passage")


def op9_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_output.write_and_read(documents(spark, sf_dir), vocabulary(TOKENIZER))


def op10_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.groups(documents(spark, sf_dir), keep="largest")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (op1_quality_rules, op2_best_fit_packing, op3_mixing, op4_token_counts, op5_quality_classifier, op6_minhash_dedup, op7_toxicity, op8_suffix_dedup, op9_token_output, op10_exact_dedup, pipeline)}

ORACLES = {"op10_exact_dedup": exact_dedup.ORACLE}
