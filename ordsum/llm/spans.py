"""Substring dedup over sliding sentence spans.

Texts are cut into sentences; what has more than `LONG` words to the next full stop is
broken at words chosen by their hash, so that equal passages break alike wherever they
stand. From each sentence on, and back from each, the shortest run of `RUN` sentences or
more with at least `LEAST` words is hashed; so every sentence of a repeated passage of that
size lies under a run within it, however short its sentences are. Hashes are gathered a part of the
documents at a time and meet in one join; sentences under any run that isn't its first occurrence are removed. Repeats of
fewer words, such as one line or a set phrase, stay.

First is the smallest (doc_id, text hash, position). Cases: null texts stay null, empty
ones empty; rows equal in id and text are one document given twice and are treated
alike; runs repeated inside one document count too; texts shorter than a run stay whole;
extra columns are kept.
"""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._shared import durable

RUN, LEAST, LONG = 3, 25, 30
#: Fewest and most words of a part of a long sentence.
PART = 5, 12
#: Runs of neighbouring documents that are dealt out together; a longer document's stay in one part.
TOGETHER = 200_000
_SENTENCE = re.compile(r"[^.!?\n]*(?:[.!?]+[^\S\n]*|\n\s*|\Z)")
_WORD = re.compile(r"\S+\s*")
_M = np.uint64(0x9E3779B97F4A7C15)


def units(text: str) -> list[str]:
    """The text in pieces that give it back when joined."""
    out = []
    for s in _SENTENCE.findall(text):
        if not s:
            continue
        if len(s) <= LONG * 2 or len(s.split()) <= LONG:
            out.append(s)
            continue
        n, part = 0, [s[: len(s) - len(s.lstrip())]]
        for w in _WORD.findall(s):
            part.append(w)
            n += 1
            if n >= PART[1] or n >= PART[0] and xxhash.xxh32_intdigest(w.strip().lower().encode("utf-8", "surrogatepass")) % 4 == 0:
                out.append("".join(part))
                n, part = 0, []
        if part:
            out.append("".join(part))
    return out


def runs(parts: list[str]) -> tuple[np.ndarray, np.ndarray, list[int], np.ndarray]:
    """Hashes of the runs, the number among worded units at which each begins, the worded units' places, and the runs' units."""
    keys, sizes, places = [], [], []
    for k, s in enumerate(parts):
        words = s.lower().split()
        if words:
            keys.append(xxhash.xxh64_intdigest(" ".join(words).encode("utf-8", "surrogatepass")))
            sizes.append(len(words))
            places.append(k)
    n = len(keys)
    x, before = np.array(keys, np.uint64), np.zeros(n + 1, np.int64)
    np.cumsum(sizes, out=before[1:])
    # forwards from each unit, and backwards from each; most runs are found both ways
    ends = np.maximum(np.arange(n) + RUN, np.searchsorted(before, before[:-1] + LEAST))
    begins = np.minimum(np.arange(1, n + 1) - RUN, np.searchsorted(before, before[1:] - LEAST, "right") - 1)
    at = np.concatenate([np.flatnonzero(ends <= n), begins[begins >= 0]])
    size = np.concatenate([ends[ends <= n], np.flatnonzero(begins >= 0) + 1]) - at
    at, size = unpack(np.unique(pack(at, size)))
    h = x[at]
    for j in range(1, int(size.max(initial=0))):
        k = np.flatnonzero(size > j)
        h[k] = (h[k] ^ (h[k] >> np.uint64(30))) * _M + x[at[k] + j]
    return h.view(np.int64), at, places, size


def pack(at, size):
    """Begin and size in one number; a run has at most max(RUN, LEAST) units, as each has a word."""
    return at * 32 + size


def unpack(run):
    return run // 32, run % 32


def met(h: np.ndarray, places: np.ndarray) -> tuple[np.ndarray, np.ndarray, list]:
    """Each hash once, with its first place and the bytes of its others (None if there are none).

    A place is four numbers: whether there is an id, the id, the text hash, the packed run. Equal places are one."""
    order = np.lexsort((*places.T[::-1], h))
    h, places = h[order], places[order]
    again = np.concatenate([[False], h[1:] == h[:-1]])
    keep = ~(again & np.concatenate([[False], (places[1:] == places[:-1]).all(axis=1)]))
    h, places, at = h[keep], places[keep], np.flatnonzero(~again[keep])
    ends = np.append(at[1:], len(h))
    more: list = [None] * len(at)
    for k in np.flatnonzero(ends - at > 1).tolist():
        more[k] = places[at[k] + 1 : ends[k]].tobytes()
    return h[at], places[at], more


def repeated_runs(docs: DataFrame) -> DataFrame:
    """(d, x, cut): begins and sizes of the non-first runs, packed, by document id and text hash; a document
    may have several rows. docs: (d, x, t).

    Runs of up to `TOGETHER` a part of neighbouring documents travel as one row a hash, so that a passage that
    all documents share costs a row a part and not one a document, there and back."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId() << 32
        h, at, of, n = [], [], [], 0

        def flush() -> pa.RecordBatch:
            key = np.repeat(np.array(of, np.int64), [len(a) for a in h], axis=0)
            a, places, more = met(np.concatenate(h), np.column_stack([key, np.concatenate(at)]))
            d = pa.array(places[:, 1], mask=places[:, 0] == 0)
            cols = [pa.array(a), pa.array(np.full(len(a), part)), d, pa.array(places[:, 2]), pa.array(places[:, 3]), pa.array(more, pa.binary())]
            return pa.RecordBatch.from_arrays(cols, names=["h", "part", "d", "x", "at", "more"])

        for batch in batches:
            for some in (batch.slice(i, 1000) for i in range(0, batch.num_rows, 1000)):
                for d, x, t in zip(*(c.to_pylist() for c in some.columns)):
                    a, b, _, size = runs(units(t))
                    if len(a):
                        h.append(a), at.append(pack(b, size)), of.append((d is not None, d or 0, x))
                        n += len(a)
                    if n >= TOGETHER:
                        yield flush()
                        part, n = part + 1, 0
                        h.clear(), at.clear(), of.clear()
        if n:
            yield flush()

    def gather(table: pa.Table) -> pa.Table:
        at, d, x, more = (c.to_pylist() for c in table.columns[1:])
        own = [(i is not None, i or 0, y, a) for a, i, y in zip(at, d, x) if a is not None]
        p = np.concatenate([np.array(own, np.int64).reshape(-1, 4), *(np.frombuffer(b, np.int64).reshape(-1, 4) for b in more if b is not None)])
        p = np.unique(p, axis=0)
        begins = np.flatnonzero(np.concatenate([[True], (p[1:, :3] != p[:-1, :3]).any(axis=1)]))
        cut = pa.ListArray.from_arrays(pa.array(np.append(begins, len(p)), pa.int32()), pa.array(p[:, 3]))
        return pa.table({"d": pa.array(p[begins, 1], mask=p[begins, 0] == 0), "x": pa.array(p[begins, 2]), "cut": cut})

    spans = durable(docs.filter(F.length("t") > 0).mapInArrow(run, "h long, part long, d long, x long, at long, more binary"), "spans")
    place, others = F.struct("d", "x", "at"), F.col("more").isNotNull()
    firsts = spans.groupBy("h").agg(F.min(place).alias("first"), F.max(place).alias("last"), F.max(others).alias("others"))
    firsts = durable(firsts.filter("first < last or others").select("h", "first"), "firsts")
    later = place > F.col("first")
    hits = spans.join(firsts, "h").filter(later | others).select("part", F.when(later, F.col("at")).alias("at"), "d", "x", "more")
    return hits.groupBy("part").applyInArrow(gather, "d long, x long, cut array<long>")


def without_repeats(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs with the repeated sentences cut from `text_col`, and n_units, n_removed added (replaced if there)."""
    src = docs.drop("n_units", "n_removed")
    d, x = F.col("doc_id").cast("long"), F.xxhash64(F.col(text_col))
    cut = repeated_runs(src.select(d.alias("d"), x.alias("x"), F.col(text_col).alias("t"))).groupBy("d", "x").agg(F.flatten(F.collect_list("cut")).alias("cut"))
    # the row travels as one column, so that no name of its own can clash
    keyed = src.select(F.struct(*src.columns).alias("row"), d.alias("rd"), x.alias("rx"))
    joined = keyed.join(cut, F.col("rd").eqNullSafe(F.col("d")) & (F.col("rx") == F.col("x")), "left")
    joined = joined.select(*[F.col("row")[c].alias(f"c{k}") for k, c in enumerate(src.columns)], "cut")
    names, at_text, at_cut = [*src.columns, "n_units", "n_removed"], src.columns.index(text_col), len(src.columns)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, total, removed = [], [], []
            for t, begins in zip(batch.column(at_text).to_pylist(), batch.column(at_cut).to_pylist()):
                if not t:
                    texts.append(t), total.append(0), removed.append(0)
                    continue
                parts = units(t)
                places = [k for k, s in enumerate(parts) if s.strip()]
                gone = {places[b + j] for b, size in map(unpack, begins or ()) for j in range(size)}
                # the white space up to the next sentence goes with a sentence
                cut_too = {k for a, b in zip(places, [*places[1:], len(parts)]) if a in gone for k in range(a, b)}
                texts.append("".join(s for k, s in enumerate(parts) if k not in cut_too) if gone else t)
                total.append(len(places)), removed.append(len(gone))
            cols = list(batch.columns[:at_cut])
            cols[at_text] = pa.array(texts, pa.string())
            yield pa.RecordBatch.from_arrays([*cols, pa.array(total, pa.int64()), pa.array(removed, pa.int64())], names=names)

    return joined.mapInArrow(run, src.withColumns({"n_units": F.lit(0).cast("long"), "n_removed": F.lit(0).cast("long")}).schema)


def op6_spans(docs: DataFrame) -> DataFrame:
    return without_repeats(docs.select("doc_id", "text"))
