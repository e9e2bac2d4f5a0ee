import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from pipeflow.llm import packing, token_counts, token_output
from pipeflow.llm.tokens import Encoder, vocabulary
from pipeflow.session import fresh_path

VOCAB = vocabulary("word_bpe_49k.json")
ROWS = [(3, "Hello, world! naïve"), (1, ""), (2, None), (7, "a " * 9000), (5, "Hello, world! naïve"), (None, "x")]


def ids(text):
    from tokenizers import Tokenizer

    return [*Tokenizer.from_file(VOCAB).encode(text or "", add_special_tokens=False).ids, 1]


def test_encoder_is_the_library():
    r = random.Random(1)
    alphabet = "abcßäöüéèñçÄÖÉÀÿø.,;!?'-  \n\tA1²ªŁ中İKÅ"
    texts = ["", "a<|endoftext|>b", "x\x1cy", "don't o'clock ...word? wo.rd,,", *("".join(r.choice(alphabet) for _ in range(40)) for _ in range(300))]
    e = Encoder(VOCAB, room=200)
    for _ in range(2):
        assert e.ids(texts) == e._whole(texts)


def docs(spark, rows=ROWS):
    return spark.createDataFrame(rows, "doc_id long, text string").withColumn("length", F.lit("clash"))


def test_files_round_trip(spark):
    folder = fresh_path(spark, "ids")
    manifest = token_output.write(docs(spark), folder, VOCAB)
    got = token_output.read(spark, folder, manifest).orderBy(F.col("doc_id").asc_nulls_first()).collect()
    at = 0
    for r, (doc_id, text) in zip(got, sorted(ROWS, key=lambda x: (x[0] is not None, x[0] or 0)), strict=True):
        want = np.array(ids(text), "<u4").tobytes()
        assert (r.doc_id, r.start, r.n_tokens, r.ids_crc32, bytes(r.ids)) == (doc_id, at, len(want) // 4, zlib.crc32(want), want)
        at += len(want) // 4
    assert token_output.write_and_read(docs(spark, []), VOCAB).count() == 0


def test_reader_fetches_single_documents_and_checks_frames(tmp_path):
    import pyarrow as pa

    path = tmp_path / "x.zst"
    packed = [np.full(k * 10, k, "<u4").tobytes() for k in range(1, 30)]
    with open(path, "wb") as f:
        w = token_output.FrameWriter(f, frame_bytes=400)
        for k, x in enumerate(packed):
            w.add(k, x)
        w.close()
    with pa.OSFile(str(path)) as f:
        reader = token_output.FrameReader(f)
        assert len(reader.table) > 5 and [x for _, x in reader.packed([20, 3])] == [packed[20], packed[3]]
    raw = bytearray(path.read_bytes())
    raw[12] ^= 1
    path.write_bytes(bytes(raw))
    with pa.OSFile(str(path)) as f, pytest.raises(Exception):  # noqa: B017
        token_output.FrameReader(f).frame(0)


def check_packing(rows, got, capacity):
    want = sorted((d, len(ids(t))) for d, t in rows if d is not None)
    sums = {}
    for r in got:
        sums[r.doc_id] = sums.get(r.doc_id, 0) + r.length
    assert sorted((d, n) for d, n in sums.items() if d is not None) == want
    by = {}
    for r in got:
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for x in by.values():
        at = 0
        for offset, n in sorted(x):
            assert offset == at
            at += n
        assert at <= capacity
    return len(by)


def test_packing(spark):
    got = packing.pack(docs(spark), VOCAB).collect()
    assert len(got) == 8 and check_packing(ROWS, got, 4096) == 3
    assert packing.pack(docs(spark, []), VOCAB).count() == 0


def best_fit(sizes, capacity):
    gaps = []
    for s in sorted(sizes, reverse=True):
        fit = [g for g in gaps if g >= s]
        if fit:
            gaps.remove(min(fit))
            gaps.append(min(fit) - s)
        else:
            gaps.append(capacity - s)
    return len(gaps)


@pytest.mark.parametrize("seed", range(20))
def test_brackets_are_paired_as_a_stack_pairs_them(seed):
    r = random.Random(seed)
    closes = np.array([r.random() < 0.6 for _ in range(60)])
    brackets = np.array([0 if c else r.randint(1, 4) for c in closes])
    stack, want = [], []
    for i, (c, n) in enumerate(zip(closes, brackets, strict=True)):
        stack += [i] * n
        want.append(stack.pop() if c and stack else -1)
    assert packing.pairs(closes, brackets)[0].tolist() == want


def packed_sizes(spark, sizes, capacity, span):
    cut = spark.createDataFrame([(k, 0, 0, n, 0) for k, n in enumerate(sizes)], packing.PIECES)
    return packing.place(cut, capacity, span).collect()


@pytest.mark.parametrize(("seed", "span"), [(0, 1 << 18), (1, 60), (2, 25)])
def test_sweeps_are_best_fit(spark, seed, span):
    r = random.Random(seed)
    sizes = [r.choice((r.randint(1, 100), r.randint(1, 20), 33)) for _ in range(250)]
    got = packed_sizes(spark, sizes, 100, span)
    by = {}
    for x in got:
        by.setdefault(x.sequence_id, []).append((x.offset, x.length))
    assert sorted(x.doc_id for x in got) == list(range(250)) and all(sizes[x.doc_id] == x.length for x in got)
    for spans in by.values():
        spans.sort()
        assert [o for o, _ in spans] == [0, *np.cumsum([n for _, n in spans])[:-1]] and sum(n for _, n in spans) <= 100
    assert len(by) <= best_fit(sizes, 100) + 1


def test_ranges_do_not_change_the_packing(spark):
    r = random.Random(9)
    sizes = [51] * 60 + [r.randint(1, 60) for _ in range(60)] + [1] * 60
    one, many = (sorted((x.sequence_id, x.offset, x.length) for x in packed_sizes(spark, sizes, 100, span)) for span in (1 << 18, 20))
    assert one == many


def test_pieces_of_more_than_half_get_a_sequence_each(spark):
    assert len({x.sequence_id for x in packed_sizes(spark, [60] * 40, 100, 15)}) == 40


def test_a_class_that_finds_no_gap_opens_sequences(spark):
    got = packed_sizes(spark, [76] * 20 + [25] * 12, 100, 15)
    assert len(got) == 32 and len({x.sequence_id for x in got}) == 23


def totals(store):
    return {(r.source, r.lang, r.tokenizer): (r.documents, r.tokens) for r in store.totals().collect()}


def test_rollup_follows_inserts_revisions_and_deletes(spark):
    schema = "doc_id long, text string, source string, lang string, deleted boolean"
    store = token_counts.Rollup(spark)
    assert totals(store) == {}
    n = lambda t: len(ids(t)) - 1
    first = spark.createDataFrame([(1, "one two", "a", "en", False), (2, "three", "a", None, None), (3, None, None, "de", False)], schema)
    assert store.apply(1, first, VOCAB, "v1") and not store.apply(1, first, VOCAB, "v1")
    assert totals(store) == {("a", "en", "v1"): (1, n("one two")), ("a", None, "v1"): (1, n("three")), (None, "de", "v1"): (1, 0)}
    second = spark.createDataFrame([(1, "one two three four", "b", "en", False), (2, None, None, None, True), (9, "gone", "a", "en", True)], schema)
    store.apply(2, second, VOCAB, "v1")
    assert totals(store) == {("b", "en", "v1"): (1, n("one two three four")), (None, "de", "v1"): (1, 0)}
    store.apply(3, first, VOCAB, "v2")
    assert totals(store)[("a", "en", "v2")] == (1, n("one two")) and len(totals(store)) == 5
    store.apply(4, spark.createDataFrame([(2, "back", "a", "en", False)], schema), VOCAB, "v1")
    assert totals(store)[("a", "en", "v1")] == (1, n("back"))


def test_rollup_goes_by_the_order_of_commits(spark):
    schema = "doc_id long, text string, source string, lang string, deleted boolean"
    store = token_counts.Rollup(spark)
    n = lambda t: len(ids(t)) - 1
    one = lambda t, deleted=False: spark.createDataFrame([(1, t, "a", "en", deleted)], schema)
    for batch, text in ((7, "ten words of it here"), (5, "four"), (8, "six words")):
        store.apply(batch, one(text), VOCAB, "v1")
    assert totals(store) == {("a", "en", "v1"): (1, n("six words"))}
    store.apply(9, one("six words"), VOCAB, "v2")
    store.apply(10, spark.createDataFrame([], schema), VOCAB, "v1")
    assert len(totals(store)) == 2
    store.apply(1, one(None, True), VOCAB, "v2")  # a delete ends every version's count
    assert totals(store) == {}


def test_registered_counts_against_brute_force(spark):
    import re

    import pyarrow.parquet as pq

    from pipeflow.llm import queries

    sf = "/root/testdata/sf0.001"
    docs, marks = (pq.read_table(f"{sf}/{t}.parquet").to_pylist() for t in ("documents", "labels"))
    poor, toxic = {m["doc_id"] for m in marks if m["quality"] == 0}, {m["doc_id"] for m in marks if m["toxic"] == 1}
    want = {}
    for d in docs:
        if d["doc_id"] in toxic:
            continue
        text = re.sub("[0-9]+", "0", d["text"]) if d["doc_id"] in poor else d["text"]
        key = (d["source"], d["lang"], "word_bpe_49k")
        a, b = want.get(key, (0, 0))
        want[key] = (a + 1, b + len(ids(text)) - 1)
    got = {(r.source, r.lang, r.tokenizer): (r.documents, r.tokens) for r in queries.op4_token_counts(spark, sf).collect()}
    assert got == want
