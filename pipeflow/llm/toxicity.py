"""Toxicity: a bidirectional gated recurrent network with attention pooling over word and character inputs, in numpy.

A word's input is its embedding (hashed table) beside the mean embeddings of its character trigrams and of its
beginnings of three to six bytes; a word of more than `LONG` bytes, as in text without blanks, is read as one piece of
at most so many bytes from each of its characters on, so all of it is read. Words and beginnings of fewer than `SEEN` training documents have no embedding. Two gated recurrent
layers read a window of words from either end; attention weighs their states, and a logistic unit reads the weighted
sum. A document is scored by all overlapping windows of its whole text; its score is the highest.

Training takes at most `most` labelled documents of each label, the first by a hash of doc_id. A document's label
holds for its window of highest word log-odds; a clean one's also for windows drawn anew in each epoch.

Null and empty texts are one window of padding and get a score too. Null ids and repeated rows are scored like others.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pipeflow.llm.common import bounded, column, map_slices, raw_texts, resident, slices, small_batches

WINDOW, STRIDE = 64, 16
WORD_ROWS, CHAR_ROWS, EMBED, HIDDEN = 1 << 16, 1 << 12, 8, 8
BEGIN = (3, 4, 5, 6)
INPUTS = 3 * EMBED
EDGE = b".,;:!?\"'()[]{}"
#: Longer words are read in pieces of at most so many bytes.
LONG = 24
#: Words after which a new part of a long text begins, a multiple of STRIDE; words that are scored together, or a part more.
PART, TOGETHER = 512 * STRIDE, 100_000
#: Standard errors by which a word must be commoner in toxic documents to mark a window, and least log-odds; documents that must hold it.
TELLING, LEAST_ODDS, SEEN = 5.0, 1.5, 5
#: What a toxic document without a telling word weighs in the loss.
WEAK = 0.25
#: Training goes on for so many steps at least, on however few documents.
STEPS, DECAY = 120, 1e-3


def word_key(word: bytes) -> bytes:
    return word.strip(EDGE).lower() or word


def pieces(word: bytes) -> Iterator[bytes]:
    """The word itself, or if it is long, what begins at each of its characters, whole characters of `LONG` bytes at most."""
    if len(word) <= LONG:
        yield word
        return
    inside = [c & 0xC0 == 0x80 for c in word] + [False]
    for at in range(len(word)):
        if inside[at]:
            continue
        end = min(at + LONG, len(word))
        while inside[end]:
            end -= 1
        yield word[at : max(end, at + 1)]


def tokens(text: bytes) -> list[bytes]:
    words = text.split()
    return words if max(map(len, words), default=0) <= LONG else [p for w in words for p in pieces(w)]


def parts(text: bytes) -> Iterator[list[bytes]]:
    """Runs of the text's tokens whose windows together are the windows of the whole text."""
    words = text.split()
    if len(words) <= PART + WINDOW and max(map(len, words), default=0) <= LONG:
        yield words
        return
    run: list[bytes] = []
    for w in words:
        for p in pieces(w):
            if len(run) == PART + WINDOW:
                yield run
                run = run[PART:]
            run.append(p)
    yield run


def word_slots(word: bytes) -> tuple[int, list[int], list[int]]:
    """Rows of the word table, of the trigram table and, for its beginnings, of the word table's upper half."""
    w = b"^" + word + b"$"
    return zlib.crc32(word) % WORD_ROWS, [zlib.crc32(w[i : i + 3]) % CHAR_ROWS for i in range(max(len(w) - 2, 1))], [WORD_ROWS + zlib.crc32(word[:k], k) % WORD_ROWS for k in BEGIN]


#: The byte table of CRC-32 with the reversed polynomial EDB88320, as in zlib.
CRC = np.arange(256, dtype=np.uint32)
for _ in range(8):
    CRC = np.where(CRC & 1, (CRC >> 1) ^ np.uint32(0xEDB88320), CRC >> 1).astype(np.uint32)


def crc_step(crc: np.ndarray, byte: np.ndarray) -> np.ndarray:
    return CRC[(crc ^ byte) & np.uint32(255)] ^ (crc >> np.uint32(8))


def all_slots(words: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """word_slots of many words that aren't empty, as arrays: word rows, trigram rows one word after another, their counts, rows of the beginnings."""
    b = np.frombuffer(b"^" + b"$^".join(words) + b"$", np.uint8).astype(np.uint32)
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(sizes + 2)
    inside = np.ones(len(b), bool)
    inside[ends - 1] = inside[ends - 2] = False  # no trigram begins there
    at = np.flatnonzero(inside)
    crc = np.full(len(at), 0xFFFFFFFF, np.uint32)
    for j in range(3):
        crc = crc_step(crc, b[at + j])
    begins = []
    for k in BEGIN:
        c = np.full(len(words), 0xFFFFFFFF ^ k, np.uint32)
        for j in range(k):
            here = j < sizes
            c = np.where(here, crc_step(c, b[np.where(here, ends - sizes - 1 + j, 0)]), c)
        begins.append(WORD_ROWS + (~c % np.uint32(WORD_ROWS)).astype(np.int64))
    rows = np.fromiter(map(zlib.crc32, words), np.uint32, len(words)) % np.uint32(WORD_ROWS)
    return rows.astype(np.int64), (~crc % np.uint32(CHAR_ROWS)).astype(np.int64), sizes, np.stack(begins, axis=1)


def sigmoid(z):
    return 0.5 * (1 + np.tanh(0.5 * z))


@dataclass
class Network:
    """Parameters by name; p["x"], p["h"], p["b"] are of both directions: (2, inputs, 3 * HIDDEN) and so on."""

    p: dict[str, np.ndarray]

    @staticmethod
    def fresh(seed: int = 0) -> Network:
        g = np.random.default_rng(seed)

        def r(*shape, scale):
            return (g.standard_normal(shape) * scale).astype(np.float32)

        return Network({"word": np.zeros((2 * WORD_ROWS, EMBED), np.float32), "char": r(CHAR_ROWS, EMBED, scale=0.1), "x": r(2, INPUTS, 3 * HIDDEN, scale=0.4), "h": r(2, HIDDEN, 3 * HIDDEN, scale=0.3), "b": np.zeros((2, 1, 3 * HIDDEN), np.float32), "att": r(2 * HIDDEN, scale=0.3), "out": r(2 * HIDDEN, scale=0.5), "bias": np.full(1, -1.0, np.float32)})

    def forward(self, x: np.ndarray, mask: np.ndarray, keep: bool = False):
        """x (T, N, INPUTS), mask (T, N) of real words -> logits (N,)."""
        p, H = self.p, HIDDEN
        T, N, _ = x.shape
        pre = np.stack([x, x[::-1]]).reshape(2, T * N, -1) @ p["x"] + p["b"]
        pre = pre.reshape(2, T, N, 3 * H)
        state, states, saved = np.zeros((2, N, H), np.float32), np.empty((2, T, N, H), np.float32), []
        for t in range(T):
            rec = state @ p["h"]
            zr = sigmoid(pre[:, t, :, : 2 * H] + rec[:, :, : 2 * H])
            z, r = zr[:, :, :H], zr[:, :, H:]
            rc = rec[:, :, 2 * H :]
            c = np.tanh(pre[:, t, :, 2 * H :] + r * rc)
            new = c + z * (state - c)
            if keep:
                saved.append((state, z, r, rc, c))
            state = states[:, t] = new
        h = np.concatenate([states[0], states[1, ::-1]], axis=2)
        e = h @ p["att"] + np.where(mask, np.float32(0), np.float32(-1e4))
        a = np.exp(e - e.max(axis=0))
        a /= a.sum(axis=0)
        pooled = np.einsum("tn,tnk->nk", a, h)
        logits = pooled @ p["out"] + p["bias"]
        return (logits, (x, h, a, pooled, saved)) if keep else logits

    def backward(self, d: np.ndarray, kept) -> tuple[dict[str, np.ndarray], np.ndarray]:
        """d: gradient of the loss by the logits. Gradients of the parameters, and of x."""
        p, H = self.p, HIDDEN
        x, h, a, pooled, saved = kept
        T, N, _ = x.shape
        g = {"out": pooled.T @ d, "bias": d.sum(keepdims=True)}
        dpool = d[:, None] * p["out"]
        da = np.einsum("nk,tnk->tn", dpool, h)
        de = a * (da - (a * da).sum(axis=0))
        dh = a[:, :, None] * dpool + de[:, :, None] * p["att"]
        g["att"] = np.einsum("tn,tnk->k", de, h)
        dstates = np.stack([dh[:, :, :H], dh[::-1, :, H:]])
        dpre, gh, carry = np.empty((2, T, N, 3 * H), np.float32), np.zeros_like(p["h"]), np.zeros((2, N, H), np.float32)
        back = np.swapaxes(p["h"], 1, 2)
        for t in range(T - 1, -1, -1):
            state, z, r, rc, c = saved[t]
            dn = dstates[:, t] + carry
            dc = dn * (1 - z) * (1 - c * c)
            drec = np.concatenate([dn * (state - c) * z * (1 - z), dc * rc * r * (1 - r), dc * r], axis=2)
            dpre[:, t, :, : 2 * H] = drec[:, :, : 2 * H]
            dpre[:, t, :, 2 * H :] = dc
            gh += np.swapaxes(state, 1, 2) @ drec
            carry = dn * z + drec @ back
        flat = dpre.reshape(2, T * N, -1)
        both = np.stack([x, x[::-1]]).reshape(2, T * N, -1)
        g["x"], g["h"], g["b"] = np.swapaxes(both, 1, 2) @ flat, gh, flat.sum(axis=1, keepdims=True)
        dx = (flat @ np.swapaxes(p["x"], 1, 2)).reshape(2, T, N, -1)
        return g, dx[0] + dx[1, ::-1]


def window_starts(n: int) -> np.ndarray:
    """Overlapping windows over n words, the last one flush with the end."""
    if n <= WINDOW:
        return np.zeros(1, np.int64)
    at = np.arange(0, n - WINDOW, STRIDE)
    return np.append(at, n - WINDOW)


def training_slots(words: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """word_slots of words that aren't empty, one row a word: word row and beginnings; trigram rows, padded with 0; what a trigram counts, padding 0."""
    word, flat, counts, begins = all_slots(words)
    inside = np.arange(counts.max()) < counts[:, None]
    grams, share = np.zeros(inside.shape, np.int32), np.zeros(inside.shape, np.float32)
    grams[inside], share[inside] = flat, np.repeat(1 / counts, counts)
    return np.column_stack([word, begins]), grams, share[:, :, None]


def _train(network: Network, arrays: list[np.ndarray], words: tuple[np.ndarray, np.ndarray, np.ndarray], y: np.ndarray, epochs: int, rate: float, seed: int) -> None:
    """arrays: word numbers of each document; words: training_slots by word number."""
    g = np.random.default_rng(seed)
    rows, grams, share = words
    width = grams.shape[1]
    seen = np.zeros(2 * WORD_ROWS, np.int64)
    for d in arrays:
        seen[np.unique(rows[d])] += 1
    known = (seen[rows] >= SEEN)[:, :, None].astype(np.float32)
    known[:, 1:] /= len(BEGIN)
    by_row = _row_odds(arrays, y, rows)
    odds = by_row[rows].max(axis=1)
    network.p["word"][:, 0] = by_row / 2  # embeddings start from what counts alone say; the network learns the rest
    trust = weights(arrays, y, odds)
    first = {k: np.zeros_like(v) for k, v in network.p.items()}
    second = {k: np.zeros_like(v) for k, v in network.p.items()}
    step = 0
    epoch = 0
    while epoch < epochs or step < STEPS:
        epoch += 1
        chosen, owner = [], []
        for i, (d, label) in enumerate(zip(arrays, y, strict=True)):
            at = window_starts(len(d))
            # the window that the words speak for most; of a clean document, the hardest one and others
            s = np.concatenate([[0], np.cumsum(odds[d])])
            best = int(at[np.argmax(s[np.minimum(at + WINDOW, len(d))] - s[at])])
            for k in {best} if label else {best, *g.choice(at, min(2, len(at)), replace=False).tolist()}:
                chosen.append(d[k : k + WINDOW])
                owner.append(i)
        # toxic windows are few: they come again, until they are a quarter of the clean ones
        owner = np.array(owner)
        toxic = np.flatnonzero(y[owner] == 1)
        again = np.tile(toxic, max(0, (len(owner) - len(toxic)) // (4 * max(len(toxic), 1)) - 1))
        owner = np.concatenate([owner, owner[again]])
        chosen += [chosen[k] for k in again]
        order = g.permutation(len(chosen))
        for i in range(0, len(order), 128):
            batch = order[i : i + 128]
            ids = np.zeros((WINDOW, len(batch)), np.int64)
            mask = np.zeros((WINDOW, len(batch)), bool)
            for j, k in enumerate(batch):
                ids[: len(chosen[k]), j], mask[: len(chosen[k]), j] = chosen[k], True
            mask &= (g.random(ids.shape) > 0.4) | (odds[ids] > 0)  # words that go, so that no window is learnt by heart
            mask[0] |= ~mask.any(axis=0)
            hide = g.random(ids.shape) < 0.3  # words that hide behind their characters, as unseen words do
            real = (mask & ~hide)[:, :, None]
            use = known[ids] * mask[:, :, None, None]
            use[:, :, 0] *= real
            w = network.p["word"][rows[ids]] * use
            c = (network.p["char"][grams[ids]] * share[ids]).sum(axis=2) * mask[:, :, None]
            logits, kept = network.forward(np.concatenate([w[:, :, 0], c, w[:, :, 1:].sum(axis=2)], axis=2).astype(np.float32), mask, True)
            d = ((sigmoid(logits) - y[owner[batch]]) * trust[owner[batch]] / len(batch)).astype(np.float32)
            grad, dx = network.backward(d, kept)
            gw, gc = np.zeros_like(network.p["word"]), np.zeros_like(network.p["char"])
            for k in range(1 + len(BEGIN)):
                part = dx[:, :, 2 * EMBED :] if k else dx[:, :, :EMBED]
                np.add.at(gw, rows[ids, k].ravel(), (part * use[:, :, k]).reshape(-1, EMBED))
            dc = dx[:, :, EMBED : 2 * EMBED] * mask[:, :, None]
            for k in range(width):
                part = share[ids, k]
                if part.any():
                    np.add.at(gc, grams[ids, k].ravel(), (dc * part).reshape(-1, EMBED))
            grad["word"], grad["char"] = gw, gc
            step += 1
            for k, v in grad.items():
                v = np.clip(v, -1, 1)
                v = v + DECAY * network.p[k] if k != "word" else v
                first[k] += 0.1 * (v - first[k])
                second[k] += 0.001 * (v * v - second[k])
                network.p[k] -= (rate * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-7)).astype(np.float32)


def weights(docs: list[np.ndarray], y: np.ndarray, odds: np.ndarray) -> np.ndarray:
    """Of each document in the loss. Labels are noisy: a toxic document without any telling word counts less, but it counts."""
    return np.array([1.0 if not label or (len(d) and odds[d].max() > 0) else WEAK for d, label in zip(docs, y, strict=True)], np.float32)


def _row_odds(docs: list[np.ndarray], y: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """What a word or a beginning says for toxicity: its log-odds where it stands in toxic documents far more often than chance allows, else 0."""
    seen = np.zeros((2, 2 * WORD_ROWS))
    for d, label in zip(docs, y, strict=True):
        seen[int(label), np.unique(rows[d])] += 1
    a, b = max((y == 1).sum(), 1), max((y == 0).sum(), 1)
    share = seen.sum(axis=0) / (a + b)
    z = (seen[1] / a - seen[0] / b) / np.sqrt(share * (1 - share) * (1 / a + 1 / b) + 1e-12)
    odds = np.log((seen[1] + 0.5) / (a + 1)) - np.log((seen[0] + 0.5) / (b + 1))
    return np.where((z > TELLING) & (odds > LEAST_ODDS) & (seen[1] >= SEEN), odds, 0)


def fit_texts(texts: Iterable[bytes], y: np.ndarray, epochs: int = 4, rate: float = 0.01, seed: int = 0) -> Network:
    """texts are read once, so that a text needn't be held beside its numbers; y: their labels."""
    network = Network.fresh(seed)
    if len(set(y.tolist())) < 2:
        return network
    numbers: dict[bytes, int] = {}
    arrays = [np.array([numbers.setdefault(word_key(w), len(numbers)) for w in tokens(t)], np.int32) for t in texts]
    words = training_slots(list(numbers) or [b"-"])
    del numbers
    _train(network, arrays, words, y, epochs, rate, seed)
    return network


def fit(docs: DataFrame, marks: DataFrame, most: int = 2000, **options) -> Network:
    """docs (doc_id, text); marks (doc_id, toxic 0 or 1). At most 2 * `most` texts reach the driver."""
    marks = marks.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    a, b = (bounded(marks.where(F.col("toxic") == v), most, "doc_id", "toxic") for v in (0, 1))
    # `most` bounds both sides, so they are broadcast
    rows = docs.select("doc_id", "text").join(F.broadcast(a.unionByName(b)), "doc_id").select("text", "toxic", F.xxhash64("doc_id").alias("h")).collect()
    rows.sort(key=lambda r: (r.h, r.toxic))
    y = np.array([r.toxic for r in rows], np.float32)
    rows.reverse()
    return fit_texts(((rows.pop().text or "").encode() for _ in range(len(rows))), y, **options)


class Scorer:
    """Scores texts; keeps the inputs of at most `room` distinct words."""

    def __init__(self, network: Network, room: int = 200_000):
        self.network, self.room = network, room
        self.table = np.zeros((1 << 14, INPUTS), np.float32)  # row 0 is padding
        self.rows: dict[bytes, int] = {}

    def _learn(self, words: set[bytes]) -> None:
        order = list(words)
        numbers: dict[bytes, int] = {}
        of = [numbers.setdefault(word_key(w), len(numbers)) for w in order]
        at = len(self.rows) + 1
        need = at + len(order)
        if need > len(self.table):
            self.table = np.concatenate([self.table, np.zeros((max(need - len(self.table), len(self.table)), INPUTS), np.float32)])
        rows, grams, counts, begins = all_slots(list(numbers))
        chars = np.add.reduceat(self.network.p["char"][grams], np.cumsum(counts) - counts) / counts[:, None]
        word = self.network.p["word"]
        x = np.concatenate([word[rows], chars, word[begins].mean(axis=1)], axis=1)
        self.table[at:need] = x[of]
        self.rows.update(zip(order, range(at, need), strict=True))

    def scores(self, texts: list[bytes]) -> np.ndarray:
        out = np.full(len(texts), -np.inf)
        docs, owner, held = [], [], 0
        for i, text in enumerate(texts):
            for part in parts(text):
                docs.append(part)
                owner.append(i)
                held += len(part)
                if held >= TOGETHER:
                    self._score(docs, owner, out)
                    docs, owner, held = [], [], 0
        if docs:
            self._score(docs, owner, out)
        return sigmoid(out)

    def _score(self, docs: list[list[bytes]], numbers: list[int], out: np.ndarray) -> None:
        """Raises out, at the numbers of docs, to the highest logit of their windows."""
        if len(self.rows) > self.room:
            self.rows = dict(islice(self.rows.items(), self.room // 2))
        missing = set().union(*docs) - self.rows.keys()
        if missing:
            self._learn(missing)
        get, ids, starts, owner, left, base = self.rows.__getitem__, [], [], [], [], 0
        for i, words in zip(numbers, docs, strict=True):
            at = window_starts(len(words))
            ids.append(np.fromiter(map(get, words), np.int64, len(words)))
            starts.append(at + base)
            left.append(np.minimum(len(words) - at, WINDOW))
            owner.append(np.full(len(at), i))
            base += len(words)
        ids.append(np.zeros(WINDOW, np.int64))
        ids, starts, left, owner = (np.concatenate(x) for x in (ids, starts, left, owner))
        for k in range(0, len(starts), 512):
            at = starts[k : k + 512]
            mask = np.arange(WINDOW)[:, None] < left[k : k + 512]
            x = self.table[np.where(mask, ids[np.minimum(at + np.arange(WINDOW)[:, None], len(ids) - 1)], 0)]
            np.maximum.at(out, owner[k : k + 512], self.network.forward(x, mask))


def score(docs: DataFrame, network: Network) -> DataFrame:
    """docs (doc_id, text) -> doc_id, score of every whole text."""
    shared = docs.sparkSession.sparkContext.broadcast(network)

    def make():
        resident()
        scorer = Scorer(shared.value)
        return lambda part: {"doc_id": column(part, "doc_id"), "score": pa.array(scorer.scores(raw_texts(part)).astype(np.float64))}

    return map_slices(docs.select(F.col("doc_id").cast("long"), "text"), "doc_id long, score double", make)


def clean(docs: DataFrame, network: Network, threshold: float = 0.3) -> DataFrame:
    """docs without the rows whose text reaches the threshold; all columns stay as they are."""
    shared = docs.sparkSession.sparkContext.broadcast(network)

    def run(batches):
        resident()
        scorer = Scorer(shared.value)
        for part in slices(batches):
            yield part.filter(pa.array(scorer.scores(raw_texts(part)) < threshold))

    small_batches(docs.sparkSession)
    return docs.mapInArrow(run, docs.schema)
