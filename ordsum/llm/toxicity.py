"""Toxicity: binary logistic regression over hashed word n-grams and skip-grams, fitted
online with FTRL-proximal. Rates are per coordinate, the L1 term leaves few weights, and
those travel to the executors as one sorted array pair.

The fit uses at most `rows` labelled rows, in a fixed pseudo-random order; scoring reads
every word of every text.

Cases: null and empty texts have no features and get the base rate's score; without any
labelled row every score is 0; several labels of one document are all learnt from (the
first of them by value decides ties in order); equal texts get equal scores.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._shared import WordIds, fold, rank_key, sigmoid

BITS = 20
ROWS = 10_000  # labelled rows that a fit uses at most
WORD = re.compile(r"[^\W_]+")
_A, _B = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


def _word_id(word: str) -> int:
    return (zlib.crc32(word.encode("utf-8", "surrogatepass")) | zlib.adler32(word.encode("utf-8", "surrogatepass")) << 32) & 0x7FFFFFFFFFFFFFFF


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(29))) * _A
    return (h >> np.uint64(64 - BITS)).astype(np.int64)


def grams(text: str | None, ids: WordIds, skip: int = 1) -> np.ndarray:
    """Sorted distinct buckets of single words, neighbouring pairs, and pairs with up to `skip` words between."""
    words = WORD.findall((text or "").lower())
    if not words:
        return np.zeros(0, np.int64)
    w = np.fromiter(map(ids.__getitem__, words), np.uint64, len(words))
    # one word many times in a row gives few features: drop repeated triples early
    parts = [_mix(np.unique(w) * _A)]
    for gap in range(1, skip + 2):
        if len(w) > gap:
            parts.append(_mix(np.unique(w[:-gap] * _B + w[gap:] + np.uint64(gap > 1))))
    flag = np.unique(np.concatenate(parts))
    return flag


class FtrlBinary:
    def __init__(self, size: int, alpha: float = 1.0, beta: float = 1.0, l1: float = 10.0, l2: float = 0.5):
        self.z, self.n = np.zeros(size), np.zeros(size)
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.bias, self.bias_n = 0.0, 1e-9

    def weights(self, at=slice(None)) -> np.ndarray:
        z, n = self.z[at], self.n[at]
        return np.where(np.abs(z) <= self.l1, 0.0, (np.sign(z) * self.l1 - z) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2))

    def learn(self, at: np.ndarray, label: int) -> None:
        w = self.weights(at)
        g = float(sigmoid(w.sum() + self.bias)) - label
        n = self.n[at]
        self.z[at] += g - (np.sqrt(n + g * g) - np.sqrt(n)) / self.alpha * w
        self.n[at] = n + g * g
        self.bias_n += g * g
        self.bias -= self.alpha * g / (self.beta + self.bias_n**0.5)


class SparseModel:
    """Non-zero weights only: sorted buckets and their values."""

    def __init__(self, buckets: np.ndarray, values: np.ndarray, bias: float):
        self.buckets, self.values, self.bias = buckets, values, bias

    def scores(self, texts: list[str | None], ids: WordIds) -> np.ndarray:
        dense = getattr(self, "_dense", None)
        if dense is None:
            dense = self._dense = np.zeros(1 << BITS)
            dense[self.buckets] = self.values
        return sigmoid(np.array([dense[grams(t, ids)].sum() for t in texts]) + self.bias)


def fit(labelled: DataFrame, rows: int = ROWS, epochs: int = 5) -> SparseModel:
    """labelled: doc_id, t, y (0 or 1)."""

    def encode(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = WordIds(_word_id)
        for batch in batches:
            got = [grams(t, ids).astype(np.int32).tobytes() for t in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(got, pa.binary()), batch.column(1), batch.column(2)], names=["g", "y", "k"])

    src = labelled.select("t", F.col("y").cast("int").alias("y"), rank_key(F.col("doc_id")).alias("k"))
    # texts become features where they lie; only features are ordered, bounded and gathered
    got = src.mapInArrow(encode, "g binary, y int, k long").orderBy("k", "y").limit(rows).collect()
    data = [(np.frombuffer(r.g, np.int32), r.y) for r in got]
    if not data:
        return SparseModel(np.zeros(0, np.int64), np.zeros(0), -35.0)
    # a bucket of one document says nothing about others
    seen = np.zeros(1 << BITS, np.int32)
    for g, _ in data:
        seen[g] += 1
    data = [(g[seen[g] > 1], y) for g, y in data]
    del got
    model = FtrlBinary(1 << BITS)
    for _ in range(epochs):
        for g, y in data:
            model.learn(g, y)
    w = model.weights()
    at = np.flatnonzero(w)
    return SparseModel(at, w[at], model.bias)


def op9_toxicity(docs: DataFrame, labels: DataFrame) -> DataFrame:
    src = docs.select("doc_id", F.col("text").cast("string").alias("t"))
    known = labels.select("doc_id", F.col("toxic").alias("y")).filter(F.col("y").isin(0, 1) & (fold(F.col("doc_id"), 4) != 2))
    # labels are bounded before texts are touched, so the join below is against few rows
    known = known.orderBy(rank_key(F.col("doc_id")), "y").limit(ROWS)
    model = fit(src.join(F.broadcast(known), "doc_id"))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = WordIds(_word_id)
        for batch in batches:
            s = model.scores(batch.column(2).to_pylist(), ids)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(s, pa.float64()), pa.array((s >= 0.3).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    held = F.coalesce(fold(F.col("doc_id"), 4) == 2, F.lit(False)).alias("held_out")
    return src.select(F.col("doc_id").cast("long"), held, "t").mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")
