"""Toxicity by non-negative positive-unlabelled learning.

Positives are documents whose label says toxic; the unlabelled set is a sample of all texts that may be learned from,
whatever their label. A linear classifier over word and word-beginning features minimises the logistic risk

    prior * risk(positives as toxic) + max(0, risk(unlabelled as clean) - prior * risk(positives as clean))

where the class prior corrects for toxic texts among the unlabelled; when the second term turns negative its gradient is
reversed, so the estimator cannot overfit below zero. Training is numpy on bounded samples (`max_positive`,
`max_unlabelled` documents, picked by hash order, so the same at every size); scoring reads every whole text, words looked
up once per worker.

Defined results: null or wordless text is scored by the bias alone; a document with several label rows is positive if any
says toxic, one with several texts is learned from with the words of all of them; null labels are no labels; with no positive at all every score is 0; repeated rows are scored one by one;
further columns are not read.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from contactscope.llm.common import pieces

WORD = re.compile(rb"[a-z0-9\x80-\xff]+")
BITS = 20
CACHE_WORDS = 300_000


def held_out():
    """Column: the documents whose labels may not be learned from."""
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1


def features_of(word: bytes) -> tuple[int, ...]:
    """Hashed features of a word: itself and its beginnings of 4 and 6 bytes."""
    mask = (1 << BITS) - 1
    out = [zlib.crc32(b"w" + word) & mask]
    out += [zlib.crc32(b"p" + word[:n]) & mask for n in (4, 6) if len(word) >= n]
    return tuple(out)


def document_features(text: bytes | None) -> np.ndarray:
    words: set[bytes] = set()
    for piece in pieces(text.lower()) if text else ():
        words.update(WORD.findall(piece))
    return np.unique(np.fromiter((f for w in words for f in features_of(w)), np.int64))


class Model:
    def __init__(self, weights: dict[int, float], bias: float):
        self.weights, self.bias = weights, bias
        self.cache: dict[bytes, tuple] = {}

    def score(self, text: bytes | None) -> float:
        found: dict[int, float] = {}
        words: set[bytes] = set()
        for piece in pieces(text.lower()) if text else ():
            words.update(WORD.findall(piece))
        cache = self.cache
        if len(cache) > CACHE_WORDS:
            cache.clear()
        for w in words:
            hit = cache.get(w)
            if hit is None:
                hit = cache[w] = tuple((f, self.weights[f]) for f in features_of(w) if f in self.weights)
            if hit:
                found.update(hit)
        return 1.0 / (1.0 + np.exp(-np.clip(self.bias + sum(found.values()), -40, 40)))


def train(positive: list[np.ndarray], unlabelled: list[np.ndarray], prior: float, steps: int = 600, rate: float = 0.08, decay: float = 1e-4, support: int = 4, evidence: float = 4.0) -> Model:
    """nnPU with Adam on all samples at once. Features are those in at least `support` positives whose
    share there exceeds that among the unlabelled by `evidence` standard errors; the rest says nothing of toxicity."""
    if not positive:
        return Model({}, -40.0)
    size = 1 << BITS
    df_p = np.bincount(np.concatenate(positive), minlength=size)
    df_u = np.bincount(np.concatenate(unlabelled), minlength=size) if unlabelled else np.zeros(size, np.int64)
    p, q = df_p / len(positive), (df_u + 1) / (len(unlabelled) + 2)
    excess = (p - q) / np.sqrt(q * (1 - q) * (1 / len(positive) + 1 / (len(unlabelled) + 1)) + 1e-12)
    chosen = np.flatnonzero((df_p >= min(support, max(1, len(positive) // 4))) & (p > 1.5 * q) & (excess > evidence))
    column = np.full(size, -1, np.int64)
    column[chosen] = np.arange(len(chosen))

    def matrix(docs: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        cols = [c[c >= 0] for c in (column[d] for d in docs)]
        rows = np.repeat(np.arange(len(docs)), [len(c) for c in cols])
        return rows, np.concatenate(cols) if cols else np.zeros(0, np.int64)

    (rp, cp), (ru, cu) = matrix(positive), matrix(unlabelled)
    n_p, n_u = len(positive), max(1, len(unlabelled))
    w, bias = np.zeros(len(chosen)), -1.0
    m, v = np.zeros(len(chosen) + 1), np.zeros(len(chosen) + 1)
    sigmoid = lambda z: 1 / (1 + np.exp(-np.clip(z, -40, 40)))
    for step in range(1, steps + 1):
        zp = np.bincount(rp, w[cp], n_p) + bias
        zu = np.bincount(ru, w[cu], len(unlabelled)) + bias
        clean = np.logaddexp(0, zu).sum() / n_u - prior * np.logaddexp(0, zp).mean()
        gp, gu = np.zeros(n_p), np.zeros(len(unlabelled))
        if clean >= 0:
            gp += prior * (sigmoid(zp) - 1) / n_p - prior * sigmoid(zp) / n_p
            gu += sigmoid(zu) / n_u
        else:
            gp += prior * sigmoid(zp) / n_p
            gu -= sigmoid(zu) / n_u
        g = np.append(np.bincount(cp, gp[rp], len(chosen)) + np.bincount(cu, gu[ru], len(chosen)) + decay * prior * w, gp.sum() + gu.sum())
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        move = rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-9)
        w, bias = w - move[:-1], bias - move[-1]
    live = np.abs(w) > 1e-3
    return Model(dict(zip(chosen[live].tolist(), w[live].tolist(), strict=True)), float(bias))


_SPACE = 1 << 40


def _hash():
    return F.pmod(F.xxhash64("doc_id"), F.lit(_SPACE))


def _below(n: int, most: int) -> int:
    """A hash below which about 1.2 * most + 100 of n ids lie."""
    return _SPACE if n <= most else min(_SPACE, int(_SPACE * (1.2 * most + 100) / n))


def _gathered(docs: DataFrame, most: int) -> list[np.ndarray]:
    """Features of the first `most` ids of docs by hash, from a little over `most` rows; a repeated id has the words of all its texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            made = [document_features(x.as_py()).astype("<i4").tobytes() for x in b.column("text").cast(pa.binary())]
            yield pa.RecordBatch.from_arrays([b.column("h"), b.column("doc_id"), pa.array(made, pa.binary())], ["h", "doc_id", "made"])

    found: dict[tuple[int, int], np.ndarray] = {}
    for r in docs.select(_hash().alias("h"), "doc_id", "text").mapInArrow(run, "h long, doc_id long, made binary").collect():
        made, key = np.frombuffer(bytes(r["made"]), "<i4").astype(np.int64), (r["h"], r["doc_id"])
        found[key] = np.union1d(found[key], made) if key in found else made
    return [found[k] for k in sorted(found)[:most]]


def fit(docs: DataFrame, labels: DataFrame, max_positive: int = 2000, max_unlabelled: int = 6000, prior: float | None = None) -> Model:
    """prior: share of toxic texts among all; estimated from the labelled rows that may be learned from when None. Samples are drawn by a bound on the
    id's hash, from counts alone: no id is shuffled for it."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where(F.col("doc_id").isNotNull() & ~held_out())
    marks = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull() & ~held_out()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    n, share, toxic = marks.agg(F.count("*"), F.avg((F.col("toxic") == 1).cast("double")), F.count_if(F.col("toxic") == 1)).first()
    if prior is None:
        prior = min(0.5, max(0.005, share or 0.0))
    if not toxic:
        return Model({}, -40.0)
    chosen = marks.where((F.col("toxic") == 1) & (_hash() < _below(toxic, max_positive))).select("doc_id")
    positive = _gathered(docs.join(F.broadcast(chosen), "doc_id", "left_semi"), max_positive)
    unlabelled = _gathered(docs.where(_hash() < _below(docs.count(), max_unlabelled)), max_unlabelled)
    return train(positive, unlabelled, prior)


def score(docs: DataFrame, model: Model, threshold: float = 0.7) -> DataFrame:
    """doc_id, held_out, score, predicted for every document."""
    model.cache = {}
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = held.value
        for b in batches:
            made = np.array([known.score(x.as_py()) for x in b.column("text").cast(pa.binary())], np.float64)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(made)], ["doc_id", "score"])

    scored = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, score double")
    return scored.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def digest(docs: DataFrame, labels: DataFrame) -> DataFrame:
    return score(docs, fit(docs, labels))
