"""Quality scores by Bradley-Terry ranking.

A document's score is linear in its features. The weights maximise the likelihood that the good document of a
pair beats the bad one, which is logistic loss on the difference of their features. A second, two-parameter
logistic fit turns scores into probabilities that the label is 1.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ontospark.llm._frames import batch, rows_of
from ontospark.llm._text import grams, spans, word_hashes
from ontospark.plans.ship import ship

#: Labelled rows that one fit uses at most, picked by a hash of their id.
SAMPLE = 20_000
BINS = 8
_KIND = np.zeros(256, np.uint8)
_KIND[48:58] = 1
_KIND[65:91] = 2
_KIND[97:123] = 3
_KIND[[c for c in range(33, 127) if not chr(c).isalnum()]] = 4
_KIND[128:] = 5
_KIND[[9, 10, 11, 12, 13, 32]] = 6
WIDTH = 24


def features(raw: bytes) -> np.ndarray:
    """Surface statistics of one text: length, character classes, repetition, line shape."""
    out = np.zeros(WIDTH, np.float32)
    if not raw:
        return out
    b, starts, ends = spans(raw)
    kind = _KIND[b]
    share = np.bincount(kind, minlength=7) / len(b)
    h = word_hashes(b, starts, ends)
    n = len(h)
    out[0] = np.log1p(len(b))
    out[1] = np.log1p(n)
    out[2:9] = share
    if not n:
        return out
    size = ends - starts
    first, last = kind[starts], kind[ends - 1]
    out[9] = size.mean()
    out[10] = size.std()
    out[11] = (first == 2).mean()
    out[12] = (last == 4).mean()
    out[13] = (size == 1).mean()
    out[14] = len(np.unique(h)) / n
    out[15] = (h[1:] == h[:-1]).mean() if n > 1 else 0
    if n >= 3:
        g = grams(h, 3)
        out[16] = 1 - len(np.unique(g)) / len(g)
    punct = kind == 4
    out[17] = (punct[1:] & punct[:-1]).sum() / n
    upper = kind == 2
    out[18] = (upper[1:] & upper[:-1]).sum() / n
    lines = np.flatnonzero(b == 10)
    edge = np.concatenate([[-1], lines, [len(b)]])
    length = np.diff(edge) - 1
    out[19] = np.log1p(length.mean())
    out[20] = len(length) / n
    at = np.searchsorted(starts, edge[:-1] + 1)
    sums = np.add.reduceat(np.append(h, np.uint64(0)), np.minimum(at, n))
    sums = sums[length > 0]
    out[21] = 1 - len(np.unique(sums)) / len(sums) if len(sums) else 0
    out[22] = (b == 124).sum() / n
    out[23] = ((kind[1:] == 1) & (kind[:-1] != 1)).sum() / n
    return out


def spread(x: np.ndarray, edges: np.ndarray) -> np.ndarray:
    """Each feature as indicators of its quantile bin."""
    bins = (x[:, :, None] > edges[None]).sum(2)
    out = np.zeros((len(x), x.shape[1] * (BINS + 1)), np.float32)
    out[np.arange(len(x))[:, None], np.arange(x.shape[1]) * (BINS + 1) + bins] = 1
    return out


class Ranker:
    def __init__(self, edges: np.ndarray, weights: np.ndarray, slope: float, shift: float):
        self.edges, self.weights, self.slope, self.shift = edges, weights, slope, shift

    def raw(self, x: np.ndarray) -> np.ndarray:
        return spread(x, self.edges) @ self.weights

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * self.raw(x) + self.shift, -40, 40)))


def _calibrate(s: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    x = np.stack([s, np.ones(len(s))], 1)
    beta = np.zeros(2)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -40, 40)))
        w = p * (1 - p) + 1e-9
        beta += np.linalg.solve((x * w[:, None]).T @ x + 1e-3 * np.eye(2), x.T @ (y - p) - 1e-3 * beta)
    return float(beta[0]), float(beta[1])


def fit(x: np.ndarray, y: np.ndarray, steps: int = 600, seed: int = 7) -> Ranker:
    """Weights from preference pairs (a row of label 1 over a row of label 0). One label only: a constant score."""
    edges = np.quantile(x, np.linspace(0, 1, BINS + 2)[1:-1], axis=0).T.astype(np.float32) if len(x) else np.zeros((WIDTH, BINS), np.float32)
    good, bad = np.flatnonzero(y == 1), np.flatnonzero(y == 0)
    w = np.zeros(x.shape[1] * (BINS + 1), np.float32)
    if not len(good) or not len(bad):
        rate = (len(good) + 1) / (len(good) + len(bad) + 2)
        return Ranker(edges, w, 0.0, float(np.log(rate / (1 - rate))))
    z, rng = spread(x, edges), np.random.default_rng(seed)
    m, v = np.zeros_like(w), np.zeros_like(w)
    for t in range(1, steps + 1):
        d = z[rng.choice(good, 1024)] - z[rng.choice(bad, 1024)]
        p = 1 / (1 + np.exp(d @ w))
        g = -(d * p[:, None]).mean(0) + 1e-4 * w
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        w -= 0.05 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    return Ranker(edges, w, *_calibrate(z @ w, y.astype(float)))


_FEATURES = pa.schema([("doc_id", pa.int64()), ("y", pa.int32()), ("x", pa.binary())])


def _features_of(batches):
    for b in batches:
        rows = [(d, y, features(body or b"").tobytes()) for d, y, body in rows_of([b], "doc_id", "quality", "body")]
        yield batch(_FEATURES, [list(c) for c in zip(*rows, strict=True)] or [[], [], []])


_SCORED = pa.schema([("doc_id", pa.int64()), ("score", pa.float64())])


def _scored(model: Ranker):
    def of(batches):
        for b in batches:
            rows = list(rows_of([b], "doc_id", "body"))
            for lo in range(0, len(rows), 2000):
                part = rows[lo : lo + 2000]
                x = np.stack([features(body or b"") for _, body in part])
                yield batch(_SCORED, [[r[0] for r in part], model.score(x).astype(float)])

    return of


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Ranker:
    """Fit on at most `sample` labelled documents; rows with a null id or a label other than 0 and 1 are left out.

    Of documents that repeat an id one is taken, the same each time.
    """
    ship(docs.sparkSession)
    picked = labels.where("doc_id IS NOT NULL AND quality IN (0, 1)").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("quality")).distinct()
    picked = picked.orderBy(F.xxhash64("doc_id"), "doc_id", "quality").limit(sample)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("body")).join(F.broadcast(picked), "doc_id")
    got = rows.select("doc_id", "quality", "body").mapInArrow(_features_of, "doc_id long, y int, x binary").groupBy("doc_id", "y").agg(F.min("x").alias("x")).collect()
    got = sorted((r[1], bytes(r[2])) for r in got)
    x = np.array([np.frombuffer(r[1], np.float32) for r in got], np.float32).reshape(-1, WIDTH)
    return fit(x, np.array([r[0] for r in got], int))


def score(docs: DataFrame, model: Ranker) -> DataFrame:
    """doc_id and score (0 to 1) for each row; null text scores as empty text. No rows: no rows."""
    ship(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("body")).mapInArrow(_scored(model), "doc_id long, score double")


def cutoff(scored: DataFrame, share: float, bins: int = 4096) -> float | None:
    """The exact (1 - share) quantile of all scores: the score of the n-th best row, n = share of the rows, rounded up.

    Each pass counts the scores in bins of the range that is left, so a task never holds more than the bins.
    """
    low, high, n = scored.where("score IS NOT NULL").agg(F.min("score"), F.max("score"), F.count("score")).first()
    if not n:
        return None
    left, above = max(1, math.ceil(share * n - 1e-9)), high
    while low < above:
        width = (above - low) / bins
        at = F.least(F.floor((F.col("score") - low) / F.lit(width)), F.lit(bins - 1)) if width > 0 else F.when(F.col("score") < above, 0).otherwise(1)
        for r in scored.where(F.col("score").between(low, above)).groupBy(at.alias("b")).agg(F.count("score").alias("n"), F.min("score").alias("low"), F.max("score").alias("high")).orderBy(F.desc("b")).collect():
            if left <= r["n"]:
                low, above = r["low"], r["high"]
                break
            left -= r["n"]
    return low


def keep_best(scored: DataFrame, share: float) -> DataFrame:
    """Rows whose score is at or above the exact (1 - share) quantile of all scores; ties at the threshold stay."""
    least = cutoff(scored, share)
    return scored.where(F.lit(True) if least is None else F.col("score") >= least)
