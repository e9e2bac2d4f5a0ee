import hashlib
import random
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from pipeflow.llm import exact_dedup, near_dedup, queries, suffix_dedup
from pipeflow.llm.common import LOWER


def frame(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string").withColumn("keep_id", F.lit("clash")).withColumn("row", F.lit(0))


def test_trie_spills_and_keeps_everything():
    r = random.Random(2)
    texts = ["".join(r.choice("ab") for _ in range(r.randint(0, 12))).encode() for _ in range(500)] + [b"p" * 50 + bytes([k]) for k in range(40)]
    trie = exact_dedup.OwnerTrie(False, budget=2000)
    for k, x in enumerate(texts):
        trie.insert(x, k, 1, [k])
    got = {t: (best, n, sorted(tags)) for t, best, n, tags in trie.owners()}
    assert got == {t: (texts.index(t), texts.count(t), [k for k, x in enumerate(texts) if x == t]) for t in set(texts)}


@pytest.mark.parametrize("keep", ["largest", "smallest"])
def test_exact_groups(spark, keep):
    rows = [(1, "Ab"), (2, "aB"), (3, "É"), (4, "é"), (5, None), (6, ""), (7, "x" * 5000), (7, "x" * 5000), (None, "ab"), (None, "lone")]
    got = exact_dedup.groups(frame(spark, rows), keep).collect()
    assert len(got) == len(rows)
    by = {}
    for d, t in rows:
        by.setdefault((t or "").encode().translate(LOWER), []).append(d)
    pick = max if keep == "largest" else min
    want = Counter()
    for d, t in rows:
        x = (t or "").encode().translate(LOWER)
        ids = [i for i in by[x] if i is not None]
        best = pick(ids) if ids else None
        want[(d, best, len(by[x]), d == best, hashlib.sha256(x).hexdigest())] += 1
    assert Counter(tuple(r) for r in got) == want
    assert exact_dedup.groups(frame(spark, []), keep).count() == 0


def test_exact_stage_keeps_columns_and_one_row(spark):
    rows = [(4, "A"), (2, "a"), (2, "a"), (9, "b"), (None, None)]
    out = exact_dedup.deduplicated(frame(spark, rows))
    assert out.columns == ["doc_id", "text", "keep_id", "row"] and sorted((r.doc_id or -1, r.text) for r in out.collect()) == [(-1, None), (2, "a"), (9, "b")]


def words(r, n, vocab=400):
    return [f"w{r.randint(0, vocab)}" for _ in range(n)]


def near_rows(seed):
    r = random.Random(seed)
    rows = []
    for _ in range(12):
        base = words(r, r.choice((3, 8, 30, 120)))
        rows.append(" ".join(base))
        for _ in range(r.randint(0, 8)):
            copy = list(base)
            for _ in range(r.randint(0, max(1, len(base) // 12))):
                copy[r.randrange(len(copy))] = r.choice(words(r, 1))
            rows.append(" ".join(copy).upper() if r.random() < 0.2 else " ".join(copy))
    rows += ["", None, "one", "One", "one two", " one\ttwo "]
    return [(i * 3, t) for i, t in enumerate(rows)]


def brute_components(rows, k):
    sets = {}
    for d, t in rows:
        w = (t or "").encode().translate(LOWER).split()
        sets[d] = {tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} if w else set()
    up = {d: d for d in sets}

    def find(a):
        while up[a] != a:
            a = up[a]
        return a

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            n = len(sets[a] & sets[b])
            if n and 100 * n >= 80 * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                up[y] = x
    return {d: (len(sets[d]), find(d)) for d in ids}


@pytest.mark.parametrize(("seed", "k"), [(1, 2), (2, 5)])
def test_near_components(spark, seed, k):
    rows = near_rows(seed)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near_dedup.components_of(frame(spark, rows).select("doc_id", "text", "row"), k).collect()}
    assert got == brute_components(rows, k)


def test_near_links_in_hot_buckets(spark):
    # texts of one template; three of them reach the threshold and meet in buckets of thousands only
    template, own = " ".join(f"t{i}" for i in range(160)), lambda d, n: " ".join(f"w{d}x{i}" for i in range(n))
    rows = [(d, f"{template} {own(d, 80)}") for d in range(2000)] + [(d, f"{template} {own(d, 17)}") for d in range(2000, 2003)]
    a, b, c = (set(near_dedup.shingle_set(rows[d][1].encode(), 5).tolist()) for d in (2000, 2001, 0))
    assert len(a & b) >= 0.8 * len(a | b) and len(a & c) < 0.8 * len(a | c)
    got = {r.doc_id: r.component_id for r in near_dedup.components_of(frame(spark, rows).select("doc_id", "text"), 5).collect()}
    assert got == {d: min(d, 2000) for d, _ in rows}


@pytest.mark.parametrize(("seed", "rounds"), [(3, 0), (4, 1)])
def test_near_close_equals_brute_force(spark, seed, rounds):
    rows = near_rows(seed)
    got = {r.row: r.component for r in near_dedup.classes(frame(spark, rows).select(F.col("doc_id").alias("row"), "text"), 2, rounds=rounds).collect()}
    assert got == {d: x[1] for d, x in brute_components(rows, 2).items()}


def test_near_repeated_ids_and_empty(spark):
    rows = [(1, "a b c d e f"), (1, "a b c d e f"), (None, "a b c d e f"), (None, "z"), (5, "")]
    got = sorted(map(str, near_dedup.components_of(frame(spark, rows).select("doc_id", "text"), 2).collect()))
    assert len(got) == 5 and sum("component_id=1" in x for x in got) == 3
    assert near_dedup.components_of(frame(spark, []).select("doc_id", "text"), 2).count() == 0
    assert near_dedup.deduplicated(frame(spark, rows)).count() == 3


def test_signature_estimates_similarity():
    r = np.random.default_rng(1)
    a = np.sort(r.integers(0, 2**63, 1000).astype(np.uint64))
    b = np.sort(np.concatenate([a[:900], r.integers(0, 2**63, 100).astype(np.uint64)]))
    got = (near_dedup.signature(a, 1024) == near_dedup.signature(b, 1024)).mean()
    assert abs(got - 900 / 1100) < 0.06
    few = near_dedup.signature(a[:3])
    assert len(few) == 128 and set(few.tolist()) <= set(a[:3].tolist())


def brute_cut(rows, w=suffix_dedup.WINDOW):
    raw = [(t or "").encode() for _, t in rows]
    c = Counter(x[i : i + w] for x in raw for i in range(len(x) - w + 1))
    out = []
    for (d, _), x in zip(rows, raw, strict=True):
        cover = np.zeros(len(x) + 1, np.int64)
        for i in range(len(x) - w + 1):
            if c[x[i : i + w]] > 1:
                cover[i] += 1
                cover[i + w] -= 1
        gone = np.cumsum(cover)[: len(x)] > 0
        kept = np.frombuffer(x, np.uint8)[~gone].tobytes()
        out.append((d, len(x), int(gone.sum()), int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum()), hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=str)


def cut_rows(seed):
    r = random.Random(seed)

    def text(n):
        return "".join(r.choice("abcdé ") for _ in range(n))

    passages = [text(n) for n in (399, 400, 401, 655, 1500, 390)]
    rows = [text(r.randint(0, 900)) + r.choice(passages) + text(r.randint(0, 700)) + r.choice(passages) for _ in range(25)]
    rows += [rows[0], rows[1], "", None, "a" * 1000, "ab" * 700, passages[4] * 3]
    return [(i, t) for i, t in enumerate(rows)]


def test_cuts(spark):
    rows = cut_rows(4)
    got = sorted((tuple(x) for x in suffix_dedup.digest(frame(spark, rows).select("doc_id", "text")).collect()), key=str)
    assert got == brute_cut(rows)


def test_cuts_with_repeated_ids_and_texts(spark):
    rows = [(1, "q" * 450), (1, None), (None, "short"), (None, "r" * 399)]
    got = sorted((tuple(x) for x in suffix_dedup.digest(frame(spark, rows).select("doc_id", "text")).collect()), key=str)
    assert got == brute_cut(rows)
    assert suffix_dedup.digest(frame(spark, []).select("doc_id", "text")).count() == 0
    out = suffix_dedup.deduplicated(spark.createDataFrame([(0, "x" * 500 + "end"), (1, "y")], "row long, text string")).orderBy("row").collect()
    assert out[0].kept in ("end", "end") and out[1].kept == "y"


def brute_shares(rows, n=51):
    lists = [re.findall(r"[^\x20\x09-\x0D]+", t or "") for _, t in rows]
    at = {}
    for k, w in enumerate(lists):
        for i in range(len(w) - n + 1):
            at.setdefault(tuple(w[i : i + n]), set()).add(k)
    return [any(len(at[tuple(w[i : i + n])]) > 1 for i in range(len(w) - n + 1)) for w in lists]


def passage_rows():
    r = random.Random(8)
    text = lambda n: " ".join(r.choice(WORDS) for _ in range(n))
    planted, short, twice, whole = text(51), text(50), text(60), text(300)
    rows = [(k, f"{text(80)} {planted} {text(r.randint(0, 90))}") for k in range(3)]  # under 400 bytes
    rows += [(k, f"{text(80)} {short}\n{text(80)}") for k in range(3, 6)]  # a word too few
    rows += [(6, f"{twice} {text(9)} {twice}"), (7, text(200)), (8, None), (9, ""), (10, "x" * 900), (11, "x" * 900)]  # no other document
    rows += [(12, whole), (13, whole), (14, whole[: len(whole) // 2] + " x " + text(40)), (15, planted.replace(" ", "\n \t")), (16, planted)]
    rows += [(17, f"{text(30)} {twice[:-1]}")]  # 59 words, in one document with two equal runs
    return rows + [(18, "é " * 60), (19, "é " * 60), (20, f"{planted[:-1]}~ {text(70)}")]


WORDS = [f"{a}{b}" for a in "bdfgklmnprst" for b in ("a", "ei", "ou", "é", "un")]


def test_passages_of_over_50_words_are_marked_whatever_their_bytes(spark, tmp_path):
    rows = passage_rows()
    frame(spark, rows).select("doc_id", "text").write.parquet(f"{tmp_path}/documents.parquet")
    out = {x.doc_id: x for x in queries.op8_suffix_dedup(spark, str(tmp_path)).collect()}
    want = brute_shares(rows)
    assert [out[d].shares_passage for d, _ in rows] == want and want[:7] == [True] * 3 + [False] * 3 + [True]
    assert not any(out[d].touched for d in (0, 1, 2))  # under 400 bytes nothing is cut
    assert [tuple(out[d])[:5] for d, _ in rows] == sorted(brute_cut(rows), key=lambda x: x[0])


def test_passages_of_random_words_equal_brute_force(spark):
    r = random.Random(4)
    rows = [(k if k % 9 else None, " ".join(r.choice("ab") for _ in range(r.randint(0, 60)))) for k in range(150)]
    for n in (7, 11, 14):
        got = suffix_dedup.digest(frame(spark, rows).select("doc_id", "text"), words=n)
        want = Counter((d, hashlib.sha256((t or "").encode()).hexdigest(), x) for (d, t), x in zip(rows, brute_shares(rows, n), strict=True))
        assert Counter((x.doc_id, x.kept_sha256, x.shares_passage) for x in got.collect()) == want


def test_words_are_hashed_alike_in_pieces(monkeypatch):
    r = random.Random(3)
    texts = ["".join(r.choice(["a", "bc", "é", "abc", " ", "\n", "  "]) for _ in range(r.randint(0, 300))).encode() for _ in range(60)] + [b"", b"\t "]
    places = lambda: {(i, s, p) for i, a, z, p, _, _ in suffix_dedup.word_runs(texts, 11) for s in range(a, z + 1)}
    whole = places()
    monkeypatch.setattr(suffix_dedup, "PIECE", 100)
    monkeypatch.setattr(suffix_dedup, "STRETCH", 13)
    assert places() == whole
    monkeypatch.setattr(suffix_dedup, "PIECE", 5)
    seen = {}
    for t in texts:
        for w, h in zip(re.findall(rb"[^\x20\x09-\x0D]+", t), suffix_dedup.long_word_hashes(t).tolist(), strict=True):
            assert seen.setdefault(w, h) == h
    assert len(set(seen.values())) == len(seen)


def test_long_texts_are_cut_in_stretches(monkeypatch):
    r = random.Random(5)
    x = bytes(r.choice(b"ab") for _ in range(5000))
    whole = {(a, z, p) for _, a, z, p, _, _ in suffix_dedup.text_runs([x])}
    monkeypatch.setattr(suffix_dedup, "STRETCH", 700)
    windows = lambda runs: {(s, p) for a, z, p in runs for s in range(a, z + 1)}
    assert windows({(a, z, p) for _, a, z, p, _, _ in suffix_dedup.text_runs([x])}) == windows(whole)


def test_equal_rows_go_into_the_trie_in_place():
    trie = exact_dedup.OwnerTrie(True, 1 << 60)
    for k in range(80_000):
        trie.insert(b"one text", k, 1, [(k, k)])
    ((text, best, n, tags),) = trie.owners()
    assert (text, best, n, len(tags)) == (b"one text", 79_999, 80_000, 80_000)


def test_columns_named_like_ours_survive(spark):
    rows = [(1, "a b c d e f g"), (2, "A b c d e f g"), (2, "z"), (None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("_row", F.lit(77)).withColumn("row", F.lit("mine")).withColumn("Row_", F.lit(0))
    for out in (exact_dedup.deduplicated(docs), near_dedup.deduplicated(docs), exact_dedup.deduplicated(docs.where("text = 'z'")), near_dedup.deduplicated(docs.where("text = 'z'"))):
        assert out.columns == docs.columns
        got = out.collect()
        assert got and all((r._row, r.row, r.Row_) == (77, "mine", 0) for r in got)


def test_small_sets_are_found(spark):
    """Sets of fewer than 50 shingles, whose densified bins repeat: every pair at the threshold is linked."""
    r = random.Random(9)
    rows = []
    for k in range(150):
        base = [f"q{k}x{i}" for i in range(r.randint(6, 45))]
        near = base[:-1] if len(base) > 9 else base
        rows += [(2 * k, " ".join(base)), (2 * k + 1, " ".join(near))]
    got = {x.doc_id: (x.n_shingles, x.component_id) for x in near_dedup.components_of(frame(spark, rows).select("doc_id", "text"), 2).collect()}
    assert got == brute_components(rows, 2)
