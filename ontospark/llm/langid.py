"""Language identification with averaged hashed subword embeddings and a linear softmax.

A text is the mean of the embeddings of its byte 2-, 3- and 4-grams (letters only, words bounded by a space),
hashed into one table. Embeddings and the linear layer are trained by stochastic gradient descent. One part
of the training sample is kept out of the descent: it sets the temperature of the softmax and the score below
which a document is rejected.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ontospark.llm._frames import batch, freeing, rows_of
from ontospark.plans.ship import ship

#: Labelled documents that one fit uses at most, picked by a hash of their id, and the bytes that their subwords may take on the driver.
SAMPLE, SAMPLE_BYTES = 4000, 256 << 20
BITS = 15
DIM = 8
PIECE = 1 << 20
_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
_LETTERS = bytes(c for c in range(256) if 65 <= c <= 90 or 97 <= c <= 122)


def has_letter(raw: bytes) -> bool:
    if raw.translate(None, _LETTERS) != raw:
        return True
    return not raw.isascii() and any(c.isalpha() for c in raw.decode("utf-8", "replace"))


def buckets(raw: bytes) -> np.ndarray:
    """Hash buckets of all subwords of a text; a run of other characters counts as one space."""
    b = np.frombuffer((b" " + raw + b" ").translate(_FOLD), np.uint8)
    space = b == 32
    keep = np.concatenate([[True], ~(space[1:] & space[:-1])])
    b = b[keep].astype(np.uint32)
    out, h = [], b * np.uint32(0x9E3779B1)
    for n in (2, 3, 4):
        if len(b) < n:
            break
        h = (h[:-1] ^ b[n - 1 :]) * np.uint32(0x85EBCA6B) + np.uint32(n)
        out.append((h ^ (h >> np.uint32(15))) * np.uint32(0x2C1B3C6D) >> np.uint32(32 - BITS))
    return np.concatenate(out) if out else np.zeros(0, np.uint32)


class Model:
    """table: what one subword adds to each language's logit; temperature and threshold come from calibration."""

    def __init__(self, langs: list[str], table: np.ndarray, bias: np.ndarray, temperature: float, threshold: float):
        self.langs, self.table, self.bias, self.temperature, self.threshold = langs, table, bias, temperature, threshold

    def logits(self, raw: bytes) -> np.ndarray:
        total, n = np.zeros(len(self.langs)), 0
        for lo in range(0, max(1, len(raw)), PIECE):  # pieces bound memory; all of the text counts
            i = buckets(raw[lo : lo + PIECE])
            n += len(i)
            total += self.table[i].sum(0) if len(i) < 1 << BITS else np.bincount(i, minlength=1 << BITS) @ self.table
        return total / max(n, 1) + self.bias

    def predict(self, raw: bytes | None) -> tuple[str, float]:
        if not self.langs or not raw or not has_letter(raw):
            return "und", 0.0
        z = self.logits(raw) * self.temperature
        p = np.exp(z - z.max())
        k = int(p.argmax())
        return self.langs[k], float(p[k] / p.sum())


def subwords(raw: bytes) -> bytes:
    """Distinct buckets of a whole text, and how often each occurs."""
    n = np.zeros(1 << BITS, np.int64)
    for lo in range(0, max(1, len(raw)), PIECE):
        n += np.bincount(buckets(raw[lo : lo + PIECE]), minlength=1 << BITS)
    u = np.flatnonzero(n)
    return u.astype("<u2").tobytes() + n[u].astype("<u4").tobytes()


def fit(texts: list[bytes], langs: list[str], epochs: int = 6, seed: int = 11) -> Model:
    return fit_subwords([subwords(t) for t in texts], langs, epochs, seed)


def fit_subwords(bags: list[bytes], langs: list[str], epochs: int = 6, seed: int = 11) -> Model:
    names = sorted(set(langs))
    if not names:
        return Model([], np.zeros((1 << BITS, 0), np.float32), np.zeros(0), 1.0, 0.0)
    y = np.array([names.index(x) for x in langs])
    rng = np.random.default_rng(seed)
    e = rng.normal(0, 0.1, (1 << BITS, DIM)).astype(np.float32)
    w, bias = rng.normal(0, 0.1, (DIM, len(names))).astype(np.float32), np.zeros(len(names), np.float32)
    docs = []
    for t in bags:
        k = len(t) // 6
        u, c = np.frombuffer(t, "<u2", k), np.frombuffer(t, "<u4", k, 2 * k)
        docs.append((u.astype(np.int64), (c / max(1, c.sum())).astype(np.float32)))
    held = np.arange(len(y)) % 5 == 4
    seen = np.flatnonzero(~held)
    for epoch in range(epochs):
        rate = 2.0 * (1 - epoch / epochs)
        for i in rng.permutation(seen):
            u, c = docs[i]
            x = c @ e[u]
            z = x @ w + bias
            p = np.exp(z - z.max())
            p /= p.sum()
            p[y[i]] -= 1
            back = w @ p
            w -= rate * 0.5 * np.outer(x, p)
            bias -= rate * 0.01 * p
            e[u] -= rate * np.outer(np.sqrt(c) * 0.5, back)
    table = e @ w
    held = np.flatnonzero(held) if held.any() else seen
    z = np.stack([docs[i][1] @ table[docs[i][0]] + bias for i in held])
    best = min((float((np.log(np.exp((z - z.max(1, keepdims=True)) * t).sum(1)) - ((z - z.max(1, keepdims=True)) * t)[np.arange(len(held)), y[held]]).mean()), t) for t in np.geomspace(0.25, 8, 21))[1]
    p = np.exp((z - z.max(1, keepdims=True)) * best)
    p /= p.sum(1, keepdims=True)
    right = p.argmax(1) == y[held]
    # a right answer of calibration is rejected at most once in a thousand, and no clear majority ever is
    threshold = min(0.5, float(np.quantile(p.max(1)[right], 0.001))) if right.any() else 0.0
    return Model(names, table.astype(np.float32), bias.astype(float), float(best), threshold)


_BAG = pa.schema([("doc_id", pa.int64()), ("lang", pa.string()), ("bag", pa.binary())])


def _bags(batches):
    for b in batches:
        rows = [(d, k, subwords(body)) for d, k, body in rows_of([b], "doc_id", "lang", "body")]
        yield batch(_BAG, [list(c) for c in zip(*rows, strict=True)] or [[], [], []])


def train(docs: DataFrame, sample: int = SAMPLE, most_bytes: int = SAMPLE_BYTES) -> Model:
    """Fit on at most `sample` documents with a language, whole texts; rows without id, text or language are left out.

    Documents are taken in the order of a hash of their id, as long as their subwords fit most_bytes together. Of rows
    that repeat id and language, one is taken, the same each time.
    """
    ship(docs.sparkSession)
    with_lang = docs.where("doc_id IS NOT NULL AND text IS NOT NULL AND lang IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id"), "lang", F.col("text").cast("binary").alias("body"))
    first = with_lang.select("doc_id", "lang", F.least(F.octet_length("body") * 3, F.lit(1 << BITS)).alias("n")).orderBy(F.xxhash64("doc_id"), "doc_id", "lang", F.desc("n")).limit(sample)
    picked, total = [], 0
    for r in first.collect():
        if picked[-1:] == [(r["doc_id"], r["lang"])]:
            continue
        total += 6 * r["n"]
        if picked and total > most_bytes:
            break
        picked.append((r["doc_id"], r["lang"]))
    if not picked:
        return fit_subwords([], [])
    chosen = F.broadcast(docs.sparkSession.createDataFrame(picked, "doc_id long, lang string"))
    bags = with_lang.join(chosen, ["doc_id", "lang"]).mapInArrow(_bags, "doc_id long, lang string, bag binary").groupBy("doc_id", "lang").agg(F.min("bag").alias("bag"))
    got = sorted((r[0], r[1], bytes(r[2])) for r in bags.toLocalIterator())
    return fit_subwords([r[2] for r in got], [r[1] for r in got])


_OUT = pa.schema([("doc_id", pa.int64()), ("lang_pred", pa.string()), ("score", pa.float64()), ("rejected", pa.bool_())])


def _predicted(model: Model):
    def of(batches):
        for b in batches:
            rows = [(d, *model.predict(body)) for d, body in rows_of([b], "doc_id", "body")]
            yield batch(_OUT, [[r[0] for r in rows], [r[1] for r in rows], [r[2] for r in rows], [r[1] == "und" or r[2] < model.threshold for r in rows]])

    return of


def identify(docs: DataFrame, model: Model) -> DataFrame:
    """One row for each row of docs: doc_id, lang_pred, score (calibrated probability), rejected.

    Text that is null or holds no letter, or a model that learned no language: `und`, score 0, rejected.
    Reads doc_id and text only. Rows that repeat a doc_id each get a row. No rows: no rows.
    """
    ship(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("body")).mapInArrow(freeing(_predicted(model)), "doc_id long, lang_pred string, score double, rejected boolean")


def drop_rejected(docs: DataFrame, model: Model) -> DataFrame:
    """The rows of docs that are not rejected, all columns as they were."""
    ship(docs.sparkSession)
    fields = docs.schema

    def of(batches):
        for b in batches:
            keep = [not (p[0] == "und" or p[1] < model.threshold) for p in (model.predict(None if t is None else t.encode("utf-8", "surrogatepass")) for t in b.column("text").to_pylist())]
            yield b.filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(freeing(of), fields)
