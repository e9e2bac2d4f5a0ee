"""Quality rules: hashed n-gram log-likelihood ratio between a trusted target and the raw corpus.

Two multinomials over hashed 1- and 2-grams are counted over every document. A document's score is the sum of
log(p_target / p_raw) over its n-grams, divided by their number; it stays if the score reaches the threshold and the
base rules pass. Null and empty texts have no n-grams: score 0, and they fail the base rules. Null ids and repeated
rows are scored like any other row; columns beside doc_id and text are not read.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pipeflow.llm.common import column, map_slices, mixed, only_marked, raw_texts, shingle_hashes, slices, small_batches, word_hashes

BLANK, SYMBOLS = b" \t\n\r\x0b\x0c", b"#*$%&|<>"
MIN_WORDS, MAX_REPEAT_PERCENT, REPEAT_WINDOW = 10, 20, 5


@dataclass(frozen=True)
class RatioModel:
    """log-ratio of each bucket: unigrams in the first half, bigrams in the second."""

    ratios: np.ndarray

    def score(self, hashes: np.ndarray) -> float:
        at = grams(hashes, len(self.ratios))
        return float(self.ratios[at].mean()) if len(at) else 0.0


def grams(hashes: np.ndarray, buckets: int) -> np.ndarray:
    half = buckets // 2
    one = (mixed(hashes) >> np.uint64(32)) % np.uint64(half)
    if len(hashes) < 2:
        return one.astype(np.int64)
    two = (shingle_hashes(hashes, 2) >> np.uint64(32)) % np.uint64(half) + np.uint64(half)
    return np.concatenate([one, two]).astype(np.int64)


def gram_counts(texts: DataFrame, buckets: int) -> np.ndarray:
    """N-grams of all texts by bucket. Each task adds up its own buckets first: at most `buckets` rows a task are shuffled, one a bucket comes to the driver."""

    def count(batches):
        total = np.zeros(buckets, np.int64)
        for part in slices(batches):
            at = [grams(word_hashes(x.split()), buckets) for x in raw_texts(part)]
            if at:
                total += np.bincount(np.concatenate(at), minlength=buckets)
        seen = np.flatnonzero(total)
        yield pa.RecordBatch.from_pydict({"bucket": pa.array(seen.astype(np.int32)), "n": pa.array(total[seen])})

    small_batches(texts.sparkSession)
    out = np.zeros(buckets)
    for r in texts.select("text").mapInArrow(count, "bucket int, n long").groupBy("bucket").agg(F.sum("n").alias("n")).collect():
        out[r.bucket] = r.n
    return out


def fit(raw: DataFrame, target_ids: DataFrame, buckets: int = 1 << 16, smoothing: float | None = None, share: float = 0.05) -> RatioModel:
    """raw (doc_id, text); target_ids (doc_id): the trusted documents, looked up by id.

    Every text of both sides is counted; only texts that may be trusted ones are shuffled, to meet their ids. The target
    is smoothed towards the raw distribution with pseudo-counts, so that an n-gram that neither side has scores 0: with
    `smoothing` of them, or with `share` times its own n-grams, so that scores don't follow the size of the corpus.
    """
    trusted = target_ids.where("doc_id is not null").select("doc_id").distinct()
    target = only_marked(raw.select("doc_id", "text"), "doc_id", trusted).join(trusted.hint("merge"), "doc_id", "left_semi")
    n = np.stack([gram_counts(raw, buckets), gram_counts(target, buckets)])
    ratios = np.zeros(buckets)
    for half in (slice(0, buckets // 2), slice(buckets // 2, buckets)):
        a, b = n[0, half], n[1, half]
        p = a / max(a.sum(), 1)
        extra = share * b.sum() if smoothing is None else smoothing
        q = (b + extra * p) / (b.sum() + extra) if b.sum() + extra else p
        with np.errstate(divide="ignore", invalid="ignore"):
            ratios[half] = np.where(a > 0, np.log(q / p), 0.0)
    return RatioModel(ratios.astype(np.float32))


def base_counts(raw: bytes, n_words: int, hashes: np.ndarray) -> tuple[int, int, int, int]:
    """word_chars, n_symbols, n_dup_lines, n_repeat_words of a text."""
    kept = raw.translate(None, BLANK)
    continuation = sum(np.bincount(np.frombuffer(kept, np.uint8) >> 6, minlength=4)[2:3].tolist()) if not kept.isascii() else 0
    symbols = len(kept) - len(kept.translate(None, SYMBOLS))
    lines = [x for x in raw.split(b"\n") if x.strip()]
    repeat = 0
    if n_words >= REPEAT_WINDOW:
        windows = shingle_hashes(hashes, REPEAT_WINDOW)
        order = np.sort(windows)
        twice = order[1:][order[1:] == order[:-1]]
        if len(twice):
            at = np.flatnonzero(np.isin(windows, twice))
            cover = np.zeros(n_words + 1, np.int64)
            np.add.at(cover, at, 1)
            np.add.at(cover, at + REPEAT_WINDOW, -1)
            repeat = int((np.cumsum(cover)[:n_words] > 0).sum())
    return len(kept) - continuation, symbols, len(lines) - len(set(lines)), repeat


SCORED = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, log_ratio double"


def apply(docs: DataFrame, model: RatioModel, threshold: float = -0.13) -> DataFrame:
    """One row a document: the base counts, the length-normalised log-ratio and the verdict."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        m = shared.value

        def score(part):
            texts = raw_texts(part)
            rows = []
            for raw in texts:
                words = raw.split()
                h = word_hashes(words)
                stats = base_counts(raw, len(words), h)
                failed = len(words) < MIN_WORDS or 100 * stats[3] > MAX_REPEAT_PERCENT * len(words)
                ratio = m.score(h)
                rows.append((len(words), *stats, failed, not failed and ratio >= threshold, ratio))
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 8
            types = [pa.int64()] * 5 + [pa.bool_()] * 2 + [pa.float64()]
            names = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "log_ratio"]
            return {"doc_id": column(part, "doc_id")} | {n: pa.array(c, t) for n, c, t in zip(names, cols, types, strict=True)}

        return score

    return map_slices(docs.select(F.col("doc_id").cast("long"), "text"), SCORED, make)
