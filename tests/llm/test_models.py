import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from pipeflow.llm import quality_classifier, quality_rules, toxicity
from pipeflow.llm.common import word_hashes

R = random.Random(7)
VOCAB = [f"word{i}" for i in range(25)]


def clean(n):
    return " ".join(R.choice(VOCAB) for _ in range(n))


def junk(n):
    return " ".join(f"{R.choice(VOCAB)}%%%" for _ in range(n))


def toxic(n):
    w = clean(n).split()
    for _ in range(3):
        w[R.randrange(n)] = R.choice(("rotter", "scoundrel"))
    return " ".join(w)


def brute_counts(text):
    words = [w for w in "".join(c if c not in " \t\n\r\x0b\x0c" else " " for c in text).split(" ") if w]
    grams = [tuple(words[i : i + 5]) for i in range(len(words) - 4)]
    covered = {i + k for i, g in enumerate(grams) if grams.count(g) > 1 for k in range(5)}
    lines = [x for x in text.split("\n") if any(c not in " \t\n\r\x0b\x0c" for c in x)]
    dup = sum(x in lines[:i] for i, x in enumerate(lines))
    return sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), dup, len(covered)


@pytest.mark.parametrize("text", ["", "a b\tc\x0bd é 中文 # *x| <y>", "x y z\nx y z\n \n\n x y z", "a b c d e f a b c d e g a b c d e", "one " * 30, "  nbsp em \x1c"])
def test_base_counts(text):
    raw = text.encode()
    w = raw.split()
    assert quality_rules.base_counts(raw, len(w), word_hashes(w)) == brute_counts(text)


def frame(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string").withColumn("score", F.lit("clash")).withColumn("kept", F.lit(1))


def test_rules_keep_clean_and_drop_junk(spark):
    rows = [(i, clean(40)) for i in range(150)] + [(i, junk(40)) for i in range(150, 200)] + [(900, None), (901, ""), (None, clean(30)), (5, clean(12)), (902, "x" * 100_000)]
    docs = frame(spark, rows)
    model = quality_rules.fit(docs, spark.range(0, 100).withColumnRenamed("id", "doc_id"), smoothing=100)
    got = quality_rules.apply(docs, model).collect()
    assert len(got) == len(rows)
    assert all(r.kept for r in got if r.doc_id is not None and r.doc_id < 150) and not any(r.kept for r in got if r.doc_id is not None and 150 <= r.doc_id)
    n = np.zeros((2, 1 << 16))
    for d, t in rows:
        at = quality_rules.grams(word_hashes((t or "").encode().split()), 1 << 16)
        n[0] += np.bincount(at, minlength=1 << 16)
        if d is not None and d < 100:
            n[1] += np.bincount(at, minlength=1 << 16)
    k = int(np.argmax(n[0, : 1 << 15]))
    p = n[0, k] / n[0, : 1 << 15].sum()
    assert model.ratios[k] == pytest.approx(np.log((n[1, k] + 100 * p) / (n[1, : 1 << 15].sum() + 100) / p), abs=1e-5)
    assert quality_rules.apply(frame(spark, []), model).count() == 0


def test_positive_unlabelled_risk_finds_junk_without_negatives(spark):
    rows = [(i, clean(R.randint(20, 60))) for i in range(300)] + [(i, junk(R.randint(20, 60))) for i in range(300, 400)] + [(900, None), (901, "")]
    docs = frame(spark, rows)
    model = quality_classifier.fit(docs, spark.range(0, 150).withColumnRenamed("id", "doc_id"))
    assert 0.5 < model.prior < 0.95
    got = {r.doc_id: r.score for r in quality_classifier.score(docs, model).collect()}
    assert len(got) == len(rows) and all(0 <= s <= 1 for s in got.values())
    assert np.mean([got[i] > 0.5 for i in range(150, 300)]) > 0.95 and np.mean([got[i] > 0.5 for i in range(300, 400)]) < 0.05
    assert quality_classifier.score(frame(spark, []), model).count() == 0


def test_gradients_are_right():
    g = np.random.default_rng(0)
    net = toxicity.Network.fresh(1)
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    x, mask = g.standard_normal((7, 3, toxicity.INPUTS)), np.ones((7, 3), bool)
    mask[4:, 1] = False
    _, kept = net.forward(x, mask, True)
    d = np.array([0.3, -0.7, 1.1])
    grad, dx = net.backward(d, kept)
    for name in ("x", "h", "b", "att", "out", "bias"):
        at = tuple(g.integers(0, n) for n in net.p[name].shape)
        losses = []
        for s in (1e-3, -1e-3):
            net.p[name][at] += s
            losses.append(float(net.forward(x, mask) @ d))
            net.p[name][at] -= s
        assert (losses[0] - losses[1]) / 2e-3 == pytest.approx(grad[name][at], rel=0.03, abs=2e-3)
    losses = []
    for s in (1e-3, -1e-3):
        x[2, 0, 5] += s
        losses.append(float(net.forward(x, mask) @ d))
        x[2, 0, 5] -= s
    assert (losses[0] - losses[1]) / 2e-3 == pytest.approx(dx[2, 0, 5], rel=0.03, abs=2e-3)


def test_windows_overlap_and_cover():
    for n in (0, 1, 64, 65, 112, 113, 1000):
        at = toxicity.window_starts(n)
        covered = {i for s in at for i in range(s, min(n, s + toxicity.WINDOW))}
        assert covered == set(range(n)) and (np.diff(at) <= toxicity.STRIDE).all()


def test_toxic_documents_are_found(spark):
    rows = [(i, clean(R.randint(10, 300))) for i in range(240)] + [(i, toxic(R.randint(10, 300))) for i in range(240, 320)] + [(900, None), (901, ""), (None, clean(20)), (902, "z" * 50_000)]
    docs = frame(spark, rows)
    marks = spark.createDataFrame([(i, int(i >= 240)) for i in range(320) if i % 4], "doc_id long, toxic int")
    net = toxicity.fit(docs, marks)
    got = {r.doc_id: r.score for r in toxicity.score(docs, net).collect()}
    assert len(got) == len(rows) and all(0 <= s <= 1 for s in got.values())
    held = [i for i in range(0, 320, 4)]
    assert np.mean([got[i] >= 0.3 for i in held if i < 240]) < 0.05 and np.mean([got[i] >= 0.3 for i in held if i >= 240]) > 0.9
    assert toxicity.clean(docs, net).columns == docs.columns and toxicity.clean(docs, net).count() < len(rows) - 60
    one = toxicity.Scorer(net, room=10)
    texts = [(t or "").encode() for _, t in rows]
    assert np.allclose(one.scores(texts[:50]), np.concatenate([one.scores(texts[:20]), one.scores(texts[20:50])]), atol=1e-5)


@pytest.mark.parametrize("letters", ["abcdefghijklmnopqrstuvwxyz", "天地玄黄宇宙洪荒日月盈昃辰宿列张寒来暑往"])
def test_all_of_a_long_word_is_read(letters):
    r = random.Random(5)
    word = "".join(r.choice(letters) for _ in range(3000)).encode()
    read = list(toxicity.pieces(word))
    assert all(len(x) <= toxicity.LONG and x.decode() for x in read) and len(read) == len(word.decode())
    slots = {x: set(toxicity.word_slots(x)[1]) for x in read}
    assert {zlib.crc32(word[i : i + 3]) % toxicity.CHAR_ROWS for i in range(len(word) - 2)} <= set().union(*slots.values())
    some = word.decode()
    assert all(x.startswith(some[i : i + 5].encode()) for i, x in enumerate(read))


def test_training_inputs_are_those_of_single_words():
    words = [b"a", b"ab", "天地".encode(), b"wretched", b"x" * 24]
    rows, grams, share = toxicity.training_slots(words)
    for i, x in enumerate(words):
        own, tri, begin = toxicity.word_slots(x)
        assert rows[i].tolist() == [own, *begin] and grams[i, : len(tri)].tolist() == tri
        assert np.allclose(share[i, : len(tri), 0], 1 / len(tri)) and not share[i, len(tri) :].any()


def test_training_on_empty_texts_only():
    net = toxicity.fit_texts(iter([b"", b" "]), np.array([0, 1], np.float32))
    assert np.isfinite(toxicity.Scorer(net).scores([b"", b"some words"])).all()


def test_abuse_inside_a_long_word_is_found():
    texts = [clean(40).encode() for _ in range(120)] + [toxic(40).encode() for _ in range(60)]
    net = toxicity.fit_texts(texts, np.array([0] * 120 + [1] * 60, np.float32))
    bad = next(w for w in max(texts[120:], key=len).split() if w not in set(b" ".join(texts[:120]).split()))
    calm = b"".join(texts[0].split()) * 30
    low, high = toxicity.Scorer(net).scores([calm, calm[:1501] + bad + calm[1501:]])
    assert low < 0.3 <= high


def test_parts_have_the_windows_of_the_whole():
    for n in (0, 5, toxicity.PART, toxicity.PART + toxicity.WINDOW, toxicity.PART + toxicity.WINDOW + 1, 3 * toxicity.PART + 77):
        words = [b"%d" % i for i in range(n)]
        want = {tuple(words[k : k + toxicity.WINDOW]) for k in toxicity.window_starts(n)}
        assert {tuple(p[k : k + toxicity.WINDOW]) for p in toxicity.parts(b" ".join(words)) for k in toxicity.window_starts(len(p))} == want


def test_passages_lie_whole_in_a_window():
    for n in (64, 65, 100, 500, 1003):
        at = toxicity.window_starts(n)
        for size in (18, 32, 49):
            assert all(((at <= k) & (k + size <= at + toxicity.WINDOW)).any() for k in range(n - size + 1))


def test_every_toxic_row_is_learnt_from():
    docs, y = [np.array(d, np.int64) for d in ([0], [1], [], [0, 1])], np.array([0, 1, 1, 1], np.float32)
    got = toxicity.weights(docs, y, np.array([2.0, 0.0]))
    assert (got > 0).all() and got[0] == got[3] == 1 and got[1] == got[2] < 1
