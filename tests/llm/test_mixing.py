from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from pipeflow.llm import mixing


def frame(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string, source string").withColumn("size", F.lit("clash")).withColumn("shard", F.lit(1))


def test_targets():
    assert mixing.targets([100, 100], [3, 1], 300) == [200.0, 100.0]
    assert mixing.targets([10, 100, 100], [3, 1, 2], 315) == pytest.approx([20, 98.33333333, 196.66666667])
    assert mixing.targets([10, 0], [1, 1], 15) == [15.0, 0.0] and mixing.targets([], [], 0) == []


def test_splitting_tree_is_exact_and_hypergeometric():
    counts = np.array([1000, 10, 0, 317])
    out = mixing.split(counts, 6, 3)
    assert out.sum(axis=0).tolist() == counts.tolist() and (out >= 0).all()
    draws = np.array([mixing.split(np.array([30, 10]), 4, s)[0] for s in range(400)])
    assert draws.sum(axis=1).tolist() == [10] * 400 and abs(draws[:, 0].mean() - 7.5) < 0.3 and draws[:, 0].std() > 0.8
    assert (mixing.split(counts, 6, 3) == out).all()


ROWS = [(i, " ".join(["w"] * (1 + i % 7)), "abc"[i % 3]) for i in range(300)] + [(1000, None, "a"), (1001, "", None), (1002, "x\x1cy\tz", None), (None, "one two", "b"), (5, "again again", "b")]


def test_draw_meets_targets(spark):
    got = mixing.draw(frame(spark, ROWS)).collect()
    assert len(got) == len(ROWS)
    taken, size, target = Counter(), Counter(), {}
    for r in got:
        assert 0 <= r.copies <= 2 and r["size"] >= 0
        taken[r.source] += r["size"] * r.copies
        size[r.source] += r["size"]
        target[r.source] = r.target
        assert len(r.shard or []) == r.copies == len(r.place or [])
    for s in target:
        assert size[s] == next(r.source_size for r in got if r.source == s)
        assert 0 <= target[s] - taken[s] <= 7.001 and target[s] <= 2 * size[s] + 1e-9
    assert sum(target.values()) == pytest.approx(1.5 * sum(size.values()))
    again = mixing.draw(frame(spark, ROWS).repartition(7)).collect()
    assert sorted(map(str, again)) == sorted(map(str, got))
    assert mixing.draw(frame(spark, [])).count() == 0


def test_mixed_rows_follow_the_draw(spark):
    out = mixing.mix(frame(spark, ROWS))
    assert out.columns == ["doc_id", "text", "source", "size", "shard"]
    counts = Counter((r.doc_id, r.text) for r in out.collect())
    assert max(counts.values()) <= 2 and set(counts) <= {(d, t) for d, t, _ in ROWS}


def taken(spark, rows):
    return {r.doc_id: r.taken for r in mixing.digest(frame(spark, rows)).collect() if r.doc_id is not None}


MANY = [(i, " ".join(["w"] * (1 + i % 5)), "ab"[i % 3 == 0]) for i in range(900)]


def test_another_tree_draws_other_documents(spark, monkeypatch):
    by_tree = taken(spark, MANY)
    whole = mixing.deal

    def all_to_the_first(pools, quotas, shards, seed):
        return [[p[:q] for p, q in zip(pools, quotas.tolist(), strict=True)]] + [[p[:0] for p in pools] for _ in range(shards - 1)]

    monkeypatch.setattr(mixing, "deal", all_to_the_first)
    flat = taken(spark, MANY)
    monkeypatch.setattr(mixing, "deal", whole)
    assert by_tree != flat and by_tree == taken(spark, MANY)
    assert sum(by_tree.values()) == pytest.approx(sum(flat.values()), abs=12)


def test_quotas_are_exact_and_blocks_disjoint():
    pools = [np.random.default_rng(k).permutation(n) for k, n in enumerate((500, 40, 0, 7))]
    quotas = np.array([211, 40, 0, 3])
    out = mixing.deal(pools, quotas, 8, [5])
    for k, q in enumerate(quotas.tolist()):
        items = np.concatenate([row[k] for row in out])
        assert len(items) == q == len(set(items.tolist())) and set(items.tolist()) <= set(pools[k].tolist())
    assert sorted({sum(map(len, row)) for row in out})[-1] - min(sum(map(len, row)) for row in out) <= 3


def test_digest_equals_brute_force(spark):
    """The draw again in plain loops, from the tree's blocks on."""
    got = {r.doc_id: (r["size"], r.source_size, r.taken) for r in mixing.digest(frame(spark, MANY)).collect()}
    key = lambda d: int(__import__("hashlib").md5(f"{d}/0".encode()).hexdigest()[:12], 16)
    docs = {s: sorted((key(d), d, len(t.split())) for d, t, x in MANY if x == s) for s in "ab"}
    sizes = [sum(n for *_, n in docs[s]) for s in "ab"]
    goal = mixing.targets(sizes, [3, 1], 1.5 * sum(sizes))
    blocks = []
    for s in "ab":
        n = min(mixing.BLOCKS, 1 << ((len(docs[s]) // mixing.PER_BLOCK).bit_length() - 1))
        by = {}
        for k, d, words in docs[s]:
            by.setdefault(k // ((1 << 48) // n), []).append((k, d, words))
        blocks.append([by[b] for b in sorted(by)])
    whole = [int(g / z + 1e-12) for g, z in zip(goal, sizes, strict=True)]
    rests = [g - w * z for g, w, z in zip(goal, whole, sizes, strict=True)]
    drawn, edges = mixing.partial_pass([np.array([sum(w for *_, w in b) for b in bs]) for bs in blocks], rests, mixing.SHARDS, 0)
    for k in range(2):
        hit = Counter(i for row in drawn for i in row[k].tolist())
        for i, block in enumerate(blocks[k]):
            rest = edges[k][1] if edges[k] and edges[k][0] == i else None
            for _, d, words in block:
                extra = hit[i]
                if rest is not None:
                    rest -= words
                    extra = int(rest >= 0)
                assert got[d] == (words, sizes[k], words * (whole[k] + extra)), d


def test_very_long_text_and_clashing_row(spark):
    docs = spark.createDataFrame([(1, "w " * 200_000, "a"), (2, "x", "a"), (2, "x", "a")], "doc_id long, text string, source string").withColumn("_row", F.col("doc_id") + 75).withColumn("row", F.lit("r")).withColumn("to", F.lit(1))
    out = mixing.mix(docs).collect()
    assert out and all(r._row == r.doc_id + 75 and r.row == "r" for r in out)
