"""A corpus pipeline of five stages: toxicity, exact and near deduplication, mixing, packing.

Each stage takes all that its predecessor kept and returns the columns of documents, the last the packed pieces. Null
and empty texts pass the filters unless they are copies; repeated rows are copies.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from pipeflow.llm import exact_dedup, mixing, near_dedup, packing, toxicity
from pipeflow.llm.common import documents, labels, saved
from pipeflow.llm.tokens import vocabulary

#: Words in a shingle, percent of the union that two near copies share.
SHINGLE, PERCENT = 5, 80


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose most toxic window reaches 0.3 go. The network learns from the labelled rows of the input's tables."""
    network = toxicity.fit(documents(spark, sf_dir), labels(spark, sf_dir))
    return toxicity.clean(docs, network)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts, but for the case of A-Z, the least doc_id stays."""
    return exact_dedup.deduplicated(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays."""
    return near_dedup.deduplicated(docs, SHINGLE, PERCENT)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources come near their targets: documents repeat up to twice, or go."""
    return mixing.mix(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of at most 4096 tokens in as few sequences as best fit finds."""
    return packing.pack(docs, vocabulary("word_bpe_49k.json"))


STAGES = [("toxicity", drop_toxic), ("exact dedup", drop_copies), ("near dedup", drop_near_copies), ("mixing", mix_sources), ("packing", pack)]

#: The toxicity stage is a trained network; tests/llm/test_pipeline.py holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = saved(docs, "stage")
    return docs
