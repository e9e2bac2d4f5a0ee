import os
from collections import Counter

import pytest

import __spark_entry__
import corpus_pipeline
from pipeflow.llm import queries
from tests.llm.test_dedup import brute_components
from tests.llm.test_tokens import check_packing

SF = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="the given tables aren't here")


def test_registered():
    assert set(queries.QUERIES) <= set(__spark_entry__.queries()) and set(queries.ORACLES) <= set(__spark_entry__.oracle_sql())
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "exact dedup", "near dedup", "mixing", "packing"]


def test_stages_one_by_one(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = corpus_pipeline.drop_toxic(spark, docs, SF)
    rows = [(r.doc_id, r.text) for r in kept.collect()]
    assert kept.columns == docs.columns and 0.5 * docs.count() < len(rows) <= docs.count()
    docs = spark.createDataFrame(kept.collect(), docs.schema)
    exact = corpus_pipeline.drop_copies(spark, docs, SF)
    best = {}
    for d, t in rows:
        key = "".join(c.lower() if c.isascii() else c for c in t or "")
        best[key] = min(d, best.get(key, d))
    assert sorted(r.doc_id for r in exact.collect()) == sorted(best.values())
    docs = spark.createDataFrame(exact.collect(), docs.schema)
    near = corpus_pipeline.drop_near_copies(spark, docs, SF)
    comps = brute_components([(r.doc_id, r.text) for r in docs.collect()], 5)
    left = [r.doc_id for r in near.collect()]
    assert near.columns == docs.columns and Counter(comps[d][1] for d in left) == Counter({c: 1 for _, c in comps.values()})
    docs = spark.createDataFrame(near.collect(), docs.schema)
    mixed = corpus_pipeline.mix_sources(spark, docs, SF)
    out = [(r.doc_id, r.text) for r in mixed.collect()]
    sizes = {r.doc_id: len((r.text or "").encode().split()) for r in docs.collect()}
    assert mixed.columns == docs.columns and max(Counter(d for d, _ in out).values()) <= 2
    assert sum(sizes[d] for d, _ in out) == pytest.approx(1.5 * sum(sizes.values()), rel=0.1)
    packed = corpus_pipeline.pack(spark, spark.createDataFrame(out, "doc_id long, text string"), SF).collect()
    by = {}
    for r in packed:
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert all(sum(n for _, n in x) <= 4096 for x in by.values())
    once = {d: t for d, t in out}
    single = corpus_pipeline.pack(spark, spark.createDataFrame(list(once.items()), "doc_id long, text string"), SF).collect()
    check_packing(list(once.items()), single, 4096)


def test_run(spark):
    assert corpus_pipeline.run(spark, SF).count() > 0
