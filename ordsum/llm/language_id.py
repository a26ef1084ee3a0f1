"""Language identification: sparse multinomial logistic regression on hashed TF-IDF
character n-grams, fitted with follow-the-regularised-leader under an elastic-net
penalty, then temperature-calibrated on rows kept out of the fit.

Document frequencies come from every row that may be learnt from; only the fit of the
weights uses a bounded sample: `per_lang` rows of each language, fewer where there are so many
languages that this were over `rows` in all (one each at least). Every fifth row of a language is
kept for the temperature.

Cases: null text or text without a letter gets `und` with score 1 (it is certain);
equal texts get equal results; an empty or label-less table gives a model without
languages, which calls every text `und` with score 0 unless it has no letter.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ._shared import LETTER, fold, rank_key

BUCKETS = 1 << 13
ORDERS = (1, 2, 3)
UNKNOWN = "und"
_MULTIPLIERS = {1: np.uint32(2654435761), 2: np.uint32(2246822519), 3: np.uint32(3266489917), 4: np.uint32(668265263)}


def counts(text: str) -> np.ndarray:
    """Hashed counts of the character n-grams of the whole text, as a dense vector."""
    x = np.frombuffer((" " + text.lower() + " ").encode("utf-32-le", "surrogatepass"), np.uint32)
    total = np.zeros(BUCKETS, np.int64)
    for n in ORDERS:
        if len(x) < n:
            break
        h = x[: len(x) - n + 1] * _MULTIPLIERS[1]
        for k in range(1, n):
            h = (h ^ (h >> np.uint32(15))) * _MULTIPLIERS[k + 1] + x[k : len(x) - n + 1 + k]
        h = (h ^ (h >> np.uint32(13))) * _MULTIPLIERS[n]
        total += np.bincount(h >> np.uint32(32 - 13), minlength=BUCKETS)
    return total


def tf_idf(c: np.ndarray, idf: np.ndarray) -> np.ndarray:
    """Rows of counts to rows of unit length: damped term frequency by inverse document frequency."""
    x = np.log1p(c).astype(np.float32) * idf
    return x / np.maximum(np.sqrt((x * x).sum(axis=-1, keepdims=True)), 1e-9)


class FtrlSoftmax:
    """Proximal FTRL for softmax regression with per-coordinate rates."""

    def __init__(self, size: int, classes: int, alpha: float = 2.0, beta: float = 1.0, l1: float = 2e-3, l2: float = 1e-3):
        self.z, self.n = np.zeros((size, classes)), np.zeros((size, classes))
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2

    def weights(self, rows=slice(None)) -> np.ndarray:
        z, n = self.z[rows], self.n[rows]
        return np.where(np.abs(z) <= self.l1, 0.0, -(z - np.sign(z) * self.l1) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2))

    def learn(self, idx: np.ndarray, val: np.ndarray, label: int) -> None:
        w = self.weights(idx)
        p = softmax(val @ w)
        p[label] -= 1.0
        g = val[:, None] * p[None, :]
        n = self.n[idx]
        self.z[idx] += g - (np.sqrt(n + g * g) - np.sqrt(n)) / self.alpha * w
        self.n[idx] = n + g * g


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def temperature(logits: np.ndarray, labels: np.ndarray) -> float:
    """The divisor of the logits that gives held-out labels the greatest likelihood (golden section on its log)."""
    if not len(labels):
        return 1.0
    loss = lambda t: -np.log(np.maximum(softmax(logits / np.exp(t))[np.arange(len(labels)), labels], 1e-12)).mean()
    lo, hi, r = -5.0, 3.0, (5**0.5 - 1) / 2
    for _ in range(40):
        a, b = hi - r * (hi - lo), lo + r * (hi - lo)
        lo, hi = (lo, b) if loss(a) < loss(b) else (a, hi)
    return float(np.exp((lo + hi) / 2))


class LanguageModel:
    def __init__(self, langs: list[str], idf: np.ndarray, weights: np.ndarray, temp: float):
        self.langs, self.idf, self.weights, self.temp = langs, idf, weights, temp

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        langs, scores = [UNKNOWN] * len(texts), [1.0] * len(texts)
        known = [i for i, t in enumerate(texts) if t and LETTER.search(t)]
        for at in range(0, len(known), 128):
            part = known[at : at + 128]
            if not self.langs:
                for i in part:
                    scores[i] = 0.0
                continue
            p = softmax(tf_idf(np.stack([counts(texts[i]) for i in part]), self.idf) @ self.weights / self.temp)
            for i, k, s in zip(part, p.argmax(1), p.max(1)):
                langs[i], scores[i] = self.langs[k], float(s)
        return langs, scores


def document_frequencies(texts: DataFrame) -> tuple[np.ndarray, int]:
    """In how many texts each bucket occurs: partial vectors per task, summed by bucket. texts: column t."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, n = np.zeros(BUCKETS, np.int64), 0
        for batch in batches:
            for t in batch.column(0).to_pylist():
                if t:
                    seen += counts(t) > 0
                    n += 1
        at = np.flatnonzero(seen)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1)), pa.array(np.append(seen[at], n))], names=["b", "n"])

    df, total = np.zeros(BUCKETS), 0
    for b, n in texts.mapInArrow(run, "b long, n long").groupBy("b").agg(F.sum("n")).collect():
        if b < 0:
            total = n
        else:
            df[b] = n
    return df, total


def fit(labelled: DataFrame, per_lang: int = 1200, rows: int = 12_000, epochs: int = 3) -> LanguageModel:
    """labelled: doc_id, t, lang; rows that may be learnt from."""
    df, total = document_frequencies(labelled.select("t"))
    idf = np.log((1 + total) / (1 + df)) + 0.1
    counted = labelled.groupBy("lang").count().collect()
    langs = sorted(r.lang for r in counted)
    number = {x: k for k, x in enumerate(langs)}
    per_lang = max(1, min(per_lang, rows // max(1, len(langs))))
    key = rank_key(F.col("doc_id"))
    # ranks are spread evenly: those under a language's bound are twice the wanted rows, however large it is
    bound = [x for r in counted for x in (F.lit(r.lang), F.lit(min((1 << 63) - 1, int((2 * per_lang / r["count"] - 0.5) * 2**64))).cast("long"))]
    likely = labelled.filter(key <= F.create_map(*bound)[F.col("lang")] if bound else F.lit(False))
    order = W.partitionBy("lang").orderBy(key, "doc_id", F.xxhash64("t"), "t")
    picked = likely.select("lang", "t", "doc_id").withColumn("r", F.row_number().over(order)).filter(F.col("r") <= per_lang)

    def encode(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for t in batch.column(1).to_pylist():
                c = counts(t)
                at = np.flatnonzero(c)
                rows.append((at.astype(np.uint16).tobytes(), c[at].astype(np.uint32).tobytes()))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), *(pa.array(c, pa.binary()) for c in zip(*rows))] if rows else [batch.column(0), batch.column(2), pa.array([], pa.binary()), pa.array([], pa.binary())], names=["lang", "r", "i", "c"])

    got = picked.select("lang", "t", "r").mapInArrow(encode, "lang string, r int, i binary, c binary").collect()
    got.sort(key=lambda r: (r.r, r.lang))
    train, held = [], []
    for r in got:
        at, c = np.frombuffer(r.i, np.uint16), np.frombuffer(r.c, np.uint32)
        (train if r.r % 5 else held).append((at, tf_idf(c, idf[at]), number[r.lang]))
    held = held or train
    model = FtrlSoftmax(BUCKETS, max(1, len(langs)))
    for _ in range(epochs):
        for x in train:
            model.learn(*x)
    w = model.weights().astype(np.float32)
    logits = np.array([v @ w[at] for at, v, _ in held]) if held else np.zeros((0, 1))
    return LanguageModel(langs, idf.astype(np.float32), w, temperature(logits, np.array([y for *_, y in held], int)))


def op2_language(docs: DataFrame) -> DataFrame:
    src = docs.select("doc_id", F.col("text").cast("string").alias("t"), "lang")
    learn = (fold(F.col("doc_id"), 4) != 2) & F.col("lang").isNotNull() & F.col("t").rlike(r"\p{L}")
    model = fit(src.filter(learn))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            langs, scores = model.predict(batch.column(2).to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(langs, pa.string()), pa.array(scores, pa.float64())], names=["doc_id", "held_out", "lang_pred", "score"])

    held = F.coalesce(fold(F.col("doc_id"), 4) == 2, F.lit(False)).alias("held_out")
    return src.select(F.col("doc_id").cast("long"), held, "t").mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double")
