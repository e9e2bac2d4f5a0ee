"""Positive-unlabelled quality classifier: non-negative unbiased risk.

Positives are trusted documents, unlabelled ones are drawn from the whole corpus; negative labels are never used. The
class prior is the least ratio of unlabelled to positive documents above a threshold of a first classifier, on
documents that it wasn't fitted to. The linear model then minimises prior * risk of positives taken as positive +
max(0, risk of unlabelled taken as negative - prior * risk of positives taken as negative) with the sigmoid loss; where
the bracket is negative, the step undoes it instead.

Fitting takes at most `most` documents of each kind, the first by a hash of doc_id; scoring reads every whole text.
Null and empty texts have zero features and get a score too. Null ids and repeated rows are scored like others.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pipeflow.llm.common import bounded, column, map_slices, mixed, raw_texts, word_hashes

HASHED, DENSE = 1024, 10
SYMBOLS = b"#*$%&|<>!@^~=+_"


def features(raw: bytes) -> np.ndarray:
    """Shares of the text: its shape first, then hashed words, root-scaled."""
    out = np.zeros(DENSE + HASHED, np.float32)
    words = raw.split()
    n = len(words)
    if not n:
        return out
    h = word_hashes(words)
    order = np.sort(h)
    distinct = 1 + int((order[1:] != order[:-1]).sum())
    chars = len(raw)
    lines = [x for x in raw.split(b"\n") if x.strip()]
    ends = sum(w[-1] < 128 and not (48 <= w[-1] <= 57 or 65 <= w[-1] <= 90 or 97 <= w[-1] <= 122) for w in words)
    out[:DENSE] = (
        1.0,
        np.log1p(n) / 10,
        (distinct / n) ** 0.5,
        float((h[1:] == h[:-1]).mean()) if n > 1 else 0.0,
        (chars - len(raw.translate(None, SYMBOLS))) / chars * 5,
        chars / n / 10,
        ends / n,
        1 - len(set(lines)) / len(lines),
        len(lines) / n,
        sum(len(w) == 1 for w in words) / n,
    )
    share = np.bincount((mixed(h) % np.uint64(HASHED)).astype(np.int64), minlength=HASHED)
    out[DENSE:] = np.sqrt(share / n)
    return out


@dataclass(frozen=True)
class LinearModel:
    weights: np.ndarray
    centre: np.ndarray
    scale: np.ndarray
    prior: float

    def score(self, x: np.ndarray) -> np.ndarray:
        z = ((x - self.centre) * self.scale) @ self.weights[:-1] + self.weights[-1]
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


class _Adam:
    def __init__(self, n: int, rate: float):
        self.m, self.v, self.t, self.rate = np.zeros(n), np.zeros(n), 0, rate

    def step(self, w: np.ndarray, g: np.ndarray) -> np.ndarray:
        self.t += 1
        self.m = 0.9 * self.m + 0.1 * g
        self.v = 0.999 * self.v + 0.001 * g * g
        return w - self.rate * (self.m / (1 - 0.9**self.t)) / (np.sqrt(self.v / (1 - 0.999**self.t)) + 1e-8)


def class_prior(p: np.ndarray, u: np.ndarray, steps: int = 200, least: float = 0.1) -> float:
    """The share of positives in u: the least, over thresholds, of the shares of u and p above a first classifier's score."""
    half_p, half_u = len(p) // 2, len(u) // 2
    x = np.vstack([p[:half_p], u[:half_u]])
    y = np.concatenate([np.full(half_p, 1.0), np.zeros(half_u)])
    by = np.where(y > 0, 0.5 / max(half_p, 1), 0.5 / max(half_u, 1))
    w, opt = np.zeros(x.shape[1] + 1), _Adam(x.shape[1] + 1, 0.02)
    for _ in range(steps):
        d = (_sigmoid(x @ w[:-1] + w[-1]) - y) * by
        w = opt.step(w, np.append(x.T @ d + 1e-4 * w[:-1], d.sum()))
    a, b = np.sort(p[half_p:] @ w[:-1]), np.sort(u[half_u:] @ w[:-1])
    best = 1.0
    for t in a[: int(len(a) * (1 - least)) : max(1, len(a) // 200)]:
        best = min(best, (1 - np.searchsorted(b, t) / len(b)) / (1 - np.searchsorted(a, t) / len(a)))
    return float(np.clip(best, 0.02, 0.98))


def fit_arrays(p: np.ndarray, u: np.ndarray, prior: float | None = None, steps: int = 600, rate: float = 0.02, decay: float = 1e-4) -> LinearModel:
    if not len(p) or not len(u):
        width = (p if len(p) else u).shape[1] if len(p) or len(u) else DENSE + HASHED
        return LinearModel(np.zeros(width + 1), np.zeros(width), np.ones(width), prior or 0.5)
    centre = u.mean(axis=0)
    spread = u.std(axis=0)
    scale = np.where(spread > 1e-6, 1 / np.maximum(spread, 1e-6), 0.0)
    # hashed words share one scale, so that their number doesn't drown the shape
    scale[DENSE:] *= 0.1
    p, u = ((x - centre) * scale for x in (p.astype(np.float64), u.astype(np.float64)))
    prior = class_prior(p, u) if prior is None else prior
    w, opt = np.zeros(p.shape[1] + 1), _Adam(p.shape[1] + 1, rate)
    for _ in range(steps):
        sp, su = _sigmoid(p @ w[:-1] + w[-1]), _sigmoid(u @ w[:-1] + w[-1])
        dp, du = sp * (1 - sp) / len(p), su * (1 - su) / len(u)
        negative = su.mean() - prior * sp.mean()  # the sigmoid loss of label -1 is sigmoid(z), of +1 it is 1 - sigmoid(z)
        if negative >= 0:
            gp, gu = -2 * prior * dp, du
        else:
            gp, gu = prior * dp, -du
        w = opt.step(w, np.append(p.T @ gp + u.T @ gu + decay * w[:-1], gp.sum() + gu.sum()))
    return LinearModel(w, centre, scale, prior)


def feature_rows(docs: DataFrame) -> DataFrame:
    """docs (doc_id, mark, text) -> doc_id, mark, features as packed floats."""

    def make():
        return lambda part: {"mark": column(part, "mark"), "x": pa.array([features(x).tobytes() for x in raw_texts(part)], pa.binary())}

    return map_slices(docs, "mark int, x binary", make)


def fit(docs: DataFrame, positives: DataFrame, most: int = 4000, prior: float | None = None) -> LinearModel:
    """docs (doc_id, text) is the unlabelled corpus; positives (doc_id) the trusted ids. At most 2 * `most` rows reach the driver."""
    p = bounded(positives.where("doc_id is not null").select("doc_id").distinct(), most, "doc_id").withColumn("mark", F.lit(1))
    u = bounded(docs.where("doc_id is not null").select("doc_id").distinct(), most, "doc_id").withColumn("mark", F.lit(0))
    # `most` bounds both sides, so they are broadcast
    picked = F.broadcast(p.unionByName(u))
    table = feature_rows(docs.select("doc_id", "text").join(picked, "doc_id").select("mark", "text")).toArrow()
    # halves and sums are the same for every order in which rows arrive
    rows = sorted(zip(table.column("x").to_pylist(), table.column("mark").to_pylist(), strict=True), key=lambda r: (zlib.crc32(r[0]), r))
    marks = np.array([m for _, m in rows])
    x = np.frombuffer(b"".join(r for r, _ in rows), np.float32).reshape(-1, DENSE + HASHED)
    return fit_arrays(x[marks == 1], x[marks == 0], prior)


def score(docs: DataFrame, model: LinearModel) -> DataFrame:
    """docs (doc_id, text) -> doc_id, score of every whole text."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        m = shared.value

        def one(part):
            x = np.array([features(t) for t in raw_texts(part)]).reshape(-1, DENSE + HASHED)
            return {"doc_id": column(part, "doc_id"), "score": pa.array(m.score(x).astype(np.float64))}

        return one

    return map_slices(docs.select(F.col("doc_id").cast("long"), "text"), "doc_id long, score double", make)
