"""Quality: gradient-boosted trees on histograms of document statistics.

Statistics of whole texts are binned at quantiles of the training sample, trees are grown
best leaf first on gradient histograms, and the finished trees are flattened into arrays
of features, thresholds and children, which numpy walks for a whole batch at once.

The fit uses at most `rows` labelled rows in a fixed pseudo-random order.

Cases: null and empty texts have all statistics zero and are scored like any other;
without labelled rows every score is 0.5 and nothing is rejected; a constant label gives
a constant score; equal texts get equal scores.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._shared import fold, rank_key, sigmoid

STATISTICS = (
    "log_bytes", "log_words", "word_length", "distinct_words", "top_word", "upper", "digit", "space",
    "newline", "stop", "comma", "bang", "pipe", "mark", "other_symbol", "non_ascii", "repeated_lines",
    "line_words", "byte_entropy", "same_neighbour", "pipe_words", "capital_words", "symbol_ends",
)
_MARKS = np.frombuffer(b"#$%&*", np.uint8)
_OTHER = np.frombuffer(b"<>{}[]()/\\=+_^~`@|;:\"", np.uint8)
_ENDS = re.compile(r"[^\w\s.,;:!?'\")\]](?:\s|$)")


def statistics(text: str | None) -> list[float]:
    if not text:
        return [0.0] * len(STATISTICS)
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    c = np.bincount(raw, minlength=256).astype(float)
    n = len(raw)
    words = text.split()
    w = len(words) or 1
    counts = Counter(words)
    top = max(counts.values(), default=0)
    lines = [x for x in text.split("\n") if x.strip()]
    p = c[c > 0] / n
    ends = len(_ENDS.findall(text))
    same = sum(map(str.__eq__, words, words[1:]))
    return [
        np.log1p(n), np.log1p(len(words)), (n - c[32] - c[10]) / w, len(counts) / w, top / w, c[65:91].sum() / n, c[48:58].sum() / n, c[32] / n,
        c[10] / n, c[46] / w, c[44] / w, c[33] / w, c[124] / w, c[_MARKS].sum() / w, c[_OTHER].sum() / w, c[128:].sum() / n, 1 - len(set(lines)) / max(1, len(lines)),
        w / max(1, len(lines)), float(-(p * np.log2(p)).sum()), same / w, counts.get("|", 0) / w, sum(map(str.isupper, counts)) / max(1, len(counts)), ends / w,
    ]


class Trees:
    """All trees in flat arrays. Leaves point to themselves, so a walk is `depth` equal steps."""

    def __init__(self, roots, feature, threshold, left, right, value, depth, base, rate):
        self.roots, self.feature, self.threshold, self.left, self.right, self.value = map(np.asarray, (roots, feature, threshold, left, right, value))
        self.depth, self.base, self.rate = depth, base, rate

    def raw(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.base)
        rows = np.arange(len(x))
        for root in self.roots:
            at = np.full(len(x), root)
            for _ in range(self.depth):
                at = np.where(x[rows, self.feature[at]] <= self.threshold[at], self.left[at], self.right[at])
            out += self.rate * self.value[at]
        return out


def boost(x: np.ndarray, y: np.ndarray, trees: int = 80, leaves: int = 8, depth: int = 4, bins: int = 64, rate: float = 0.15, l2: float = 2.0, least: int = 10) -> Trees:
    if not len(y):
        return Trees([], [], [], [], [], [], 0, 0.0, rate)
    cuts = [np.unique(np.quantile(col, np.linspace(0, 1, bins + 1)[1:-1], method="lower")) for col in x.T]
    binned = np.stack([np.searchsorted(q, col, side="left") for q, col in zip(cuts, x.T)], axis=1)  # bin <= b iff value <= cut[b]
    m = x.shape[1]
    flat = binned + np.arange(m) * bins
    base = float(np.log((y.mean() * len(y) + 0.5) / ((1 - y.mean()) * len(y) + 0.5)))
    score = np.full(len(y), base)
    roots, feature, threshold, left, right, value = [], [], [], [], [], []

    def node(v: float) -> int:
        k = len(feature)
        feature.append(0), threshold.append(np.inf), left.append(k), right.append(k), value.append(v)
        return k

    def best(rows: np.ndarray, g: np.ndarray, h: np.ndarray):
        idx = flat[rows].ravel()
        hist = lambda v: np.bincount(idx, v, bins * m).reshape(m, bins).cumsum(1)
        sg, sh, sn = hist(np.repeat(g[rows], m)), hist(np.repeat(h[rows], m)), hist(np.ones(len(idx)))
        tg, th, tn = sg[:, -1:], sh[:, -1:], sn[:, -1:]
        gain = sg**2 / (sh + l2) + (tg - sg) ** 2 / (th - sh + l2) - tg**2 / (th + l2)
        gain[(sn < least) | (tn - sn < least)] = -1
        k = int(gain.argmax())
        return float(gain.flat[k]), k // bins, k % bins

    for _ in range(trees):
        p = sigmoid(score)
        g, h = p - y, np.maximum(p * (1 - p), 1e-6)
        leaf = lambda rows: float(-g[rows].sum() / (h[rows].sum() + l2))
        rows = np.arange(len(y))
        root = node(leaf(rows))
        roots.append(root)
        open_ = [(*best(rows, g, h), root, rows, 0)]
        for _ in range(leaves - 1):
            k = max(range(len(open_)), key=lambda i: open_[i][0], default=None)
            if k is None or open_[k][0] <= 1e-6:
                break
            _, f, b, at, rows, d = open_.pop(k)
            go = binned[rows, f] <= b
            feature[at], threshold[at] = f, float(cuts[f][b])
            for side, part in ((left, rows[go]), (right, rows[~go])):
                side[at] = child = node(leaf(part))
                if d + 1 < depth and len(part) >= 2 * least:
                    open_.append((*best(part, g, h), child, part, d + 1))
        one = Trees([root], feature, threshold, left, right, value, depth, 0.0, rate)
        score += one.raw(x)
    return Trees(roots, feature, threshold, left, right, value, depth, base, rate)


def fit(labelled: DataFrame, rows: int = 12_000) -> Trees:
    """labelled: doc_id, t, y (0 or 1)."""

    def encode(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = [statistics(t) for t in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(got, pa.list_(pa.float64())), batch.column(1), batch.column(2)], names=["x", "y", "k"])

    top = labelled.select("t", F.col("y").cast("int").alias("y"), rank_key(F.col("doc_id")).alias("k")).orderBy("k", "y").limit(rows)
    got = sorted(top.mapInArrow(encode, "x array<double>, y int, k long").collect(), key=lambda r: (r.k, r.y))
    return boost(np.array([r.x for r in got]).reshape(-1, len(STATISTICS)), np.array([r.y for r in got], float))


def train(docs: DataFrame, labels: DataFrame, rows: int = 12_000) -> Trees:
    """Learns from labelled rows of the training folds, at most `rows` of them."""
    src = docs.select("doc_id", F.col("text").cast("string").alias("t"))
    known = labels.select("doc_id", F.col("quality").alias("y")).filter(F.col("y").isin(0, 1) & (fold(F.col("doc_id"), 5) != 0))
    known = known.orderBy(rank_key(F.col("doc_id")), "y").limit(rows)
    return fit(src.join(F.broadcast(known), "doc_id"), rows)


def with_score(df: DataFrame, model: Trees, text_col: str = "text", out_col: str = "quality_score") -> DataFrame:
    """df with one more column, the score of the whole text. An existing column of that name is replaced."""
    others = [c for c in df.columns if c != out_col]
    src = df.select(*others)
    at = others.index(text_col)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.array([statistics(t) for t in batch.column(at).to_pylist()]).reshape(-1, len(STATISTICS))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(sigmoid(model.raw(x)), pa.float64())], names=[*others, out_col])

    return src.mapInArrow(run, src.withColumn(out_col, F.lit(0.0)).schema)


def op10_quality(docs: DataFrame, labels: DataFrame) -> DataFrame:
    model = train(docs, labels)
    src = docs.select(F.col("doc_id").cast("long"), F.coalesce(fold(F.col("doc_id"), 5) == 0, F.lit(False)).alias("held_out"), F.col("text").cast("string").alias("t"))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.array([statistics(t) for t in batch.column(2).to_pylist()]).reshape(-1, len(STATISTICS))
            s = sigmoid(model.raw(x))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(s), pa.array((s >= 0.3).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    return src.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")
