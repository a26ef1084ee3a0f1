"""Benchmark decontamination by greedy string tiling.

A rolling Karp-Rabin hash over `min_match` tokens finds the seeds that a document shares
with benchmark items; seeds on one diagonal join into runs. The longest run of unmarked
tokens is marked as a tile, again and again, until none of `min_match` tokens is left.
The share of an item's tokens under tiles is its coverage, so passages whose sentences
come in another order are still found.

The benchmark is a query set: it is read in blocks of at most `block_tokens` tokens
(few hundred MB on no machine), and each block is held against all documents.

Cases: null and empty texts match nothing; an item of fewer than `min_match` tokens
matches nothing; texts that repeat themselves, however long, take memory in proportion to their
length; an empty benchmark gives no rows; equal runs are tiled at the smallest
document position, then item position; repeated rows are reported once each.
"""

from __future__ import annotations

import heapq
import re
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._shared import WordIds

WORD = re.compile(r"[^\W_]+")
_M = np.uint64(0x9E3779B97F4A7C15)
_BITS = 22


def word_id(w: str) -> int:
    b = w.encode("utf-8", "surrogatepass")
    return zlib.crc32(b) | (zlib.adler32(b) ^ len(b) << 16) << 32


def tokens(text: str | None, ids: WordIds) -> np.ndarray:
    words = WORD.findall(text.lower()) if text else []
    return np.fromiter(map(ids.__getitem__, words), np.uint64, len(words))


def rolling(t: np.ndarray, k: int) -> np.ndarray:
    """Hash of each run of k tokens; wraps modulo 2^64."""
    if len(t) < k:
        return np.zeros(0, np.uint64)
    h = t[: len(t) - k + 1].copy()
    for j in range(1, k):
        h = h * _M + t[j : len(t) - k + 1 + j]
    return h ^ (h >> np.uint64(31))


def tile(pairs: np.ndarray, k: int) -> list[tuple[int, int, int]]:
    """Greedy tiles (position, position, length) from the seeds (rows of two positions) of k equal tokens."""
    d = pairs[:, 0] - pairs[:, 1]
    order = np.lexsort((pairs[:, 0], d))
    pairs, d = pairs[order], d[order]
    new = np.flatnonzero(np.r_[True, (np.diff(d) != 0) | (np.diff(pairs[:, 0]) != 1)])
    ends = np.r_[new[1:], len(pairs)]
    heap = [(-(e - s + k - 1), int(pairs[s, 0]), int(pairs[s, 1])) for s, e in zip(new, ends)]
    heap = [(int(n), a, b) for n, a, b in heap]
    heapq.heapify(heap)
    used_a: set[int] = set()
    used_b: set[int] = set()
    tiles = []
    while heap:
        n, a, b = heapq.heappop(heap)
        n = -n
        free = [a + j not in used_a and b + j not in used_b for j in range(n)]
        if all(free):
            tiles.append((a, b, n))
            used_a.update(range(a, a + n))
            used_b.update(range(b, b + n))
            continue
        j = 0
        while j < n:
            if free[j]:
                e = j
                while e < n and free[e]:
                    e += 1
                if e - j >= k:
                    heapq.heappush(heap, (-(e - j), a + j, b + j))
                j = e
            else:
                j += 1
    return tiles


def tile_by_search(a: np.ndarray, b: np.ndarray, k: int) -> list[tuple[int, int, int]]:
    """The same tiles without a list of seeds, for repetitive texts that have very many: the length of the longest
    common run of unmarked tokens is searched by halving, each trial one set of hashes of all runs of a length."""

    def sums(t):
        """Running sums of tokens times powers, and the powers' inverses: the hash of any run is a difference."""
        up = np.full(len(t) + 1, _M)
        down = np.full(len(t) + 1, np.uint64(pow(int(_M), -1, 1 << 64)))
        up[0] = down[0] = 1
        up, down = np.multiply.accumulate(up), np.multiply.accumulate(down)
        return np.r_[np.uint64(0), np.cumsum(t * up[: len(t)], dtype=np.uint64)], down

    sides = [[sums(t), np.zeros(len(t), bool)] for t in (a, b)]

    def windows(side, n):
        (c, down), used = side
        if len(used) < n:
            return np.zeros(0, np.int64), np.zeros(0, np.uint64)
        marks = np.r_[0, np.cumsum(used)]
        at = np.flatnonzero(marks[n:] == marks[:-n])
        return at, (c[at + n] - c[at]) * down[at]

    def common(n):
        at, h = windows(sides[0], n)
        bt, g = windows(sides[1], n)
        hit = np.flatnonzero(np.isin(h, g))
        return (int(at[hit[0]]), int(bt[np.flatnonzero(g == h[hit[0]])[0]])) if len(hit) else None

    tiles = []
    while (found := common(k)) is not None:
        lo, hi = k, min(len(a), len(b))
        while lo < hi:
            n = (lo + hi + 1) // 2
            got = common(n)
            if got is None:
                hi = n - 1
            else:
                lo, found = n, got
        i, j = found
        tiles.append((i, j, lo))
        sides[0][1][i : i + lo] = True
        sides[1][1][j : j + lo] = True
    return tiles


#: Seeds of one document that are listed; beyond that its tiles are searched without a list.
SEEDS = 200_000


class Seeds:
    """The benchmark's k-token runs, sorted by hash, behind a bitmap."""

    def __init__(self, items: list[tuple[int, str | None]], k: int):
        ids = WordIds(word_id)
        self.k, self.ids, self.sizes = k, [i for i, _ in items], []
        hashes, owner, place = [], [], []
        self.tokens = []
        for n, (_, text) in enumerate(items):
            t = tokens(text, ids)
            h = rolling(t, k)
            self.sizes.append(len(t))
            self.tokens.append(t)
            hashes.append(h), owner.append(np.full(len(h), n)), place.append(np.arange(len(h)))
        h = np.concatenate(hashes) if hashes else np.zeros(0, np.uint64)
        order = np.argsort(h, kind="stable")
        self.hash = h[order]
        self.owner = (np.concatenate(owner) if owner else np.zeros(0, int))[order]
        self.place = (np.concatenate(place) if place else np.zeros(0, int))[order]
        self.bitmap = np.zeros(1 << _BITS, bool)
        self.bitmap[(self.hash >> np.uint64(64 - _BITS)).astype(np.int64)] = True

    def tiles(self, t: np.ndarray) -> Iterator[tuple[int, list[tuple[int, int, int]]]]:
        """(item number, tiles) of each item that a document shares a seed with."""
        found = self.matches(t)
        if isinstance(found, dict):
            for item, pairs in found.items():
                yield item, tile(pairs, self.k)
            return
        for item in found:
            got = tile_by_search(t, self.tokens[item], self.k)
            if got:
                yield int(item), got

    def matches(self, t: np.ndarray) -> dict[int, np.ndarray] | np.ndarray:
        """Item number -> (document position, item position) of the seeds that a document shares with it; where
        these are more than SEEDS, the item numbers alone."""
        h = rolling(t, self.k)
        at = np.flatnonzero(self.bitmap[(h >> np.uint64(64 - _BITS)).astype(np.int64)])
        if not len(at):
            return {}
        lo, hi = np.searchsorted(self.hash, h[at], "left"), np.searchsorted(self.hash, h[at], "right")
        n = hi - lo
        at, lo, n = at[n > 0], lo[n > 0], n[n > 0]
        if not len(at):
            return {}
        if n.sum() > SEEDS:
            first = np.unique(lo)
            ends = np.searchsorted(self.hash, self.hash[first], "right")
            return np.unique(np.concatenate([self.owner[x:y] for x, y in zip(first, ends)]))
        rows = np.repeat(lo - np.r_[0, np.cumsum(n)[:-1]], n) + np.arange(n.sum())
        doc = np.repeat(at, n)
        owner, place = self.owner[rows], self.place[rows]
        out = {}
        for item in np.unique(owner):
            keep = owner == item
            d, p = doc[keep], place[keep]
            same = np.all([t[d + j] == self.tokens[item][p + j] for j in range(self.k)], axis=0)
            if same.any():
                out[int(item)] = np.stack([d[same], p[same]], axis=1)
        return out


def overlaps(docs: DataFrame, benchmark: DataFrame, min_match: int = 5, block_tokens: int = 2_000_000) -> DataFrame:
    """(doc_id, item_id, n_tiles, longest, tiled, item_tokens, coverage) of each document and item that share a seed."""
    bench = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("b"))
    total = bench.select(F.sum(F.length("b")).alias("n")).first().n or 0
    blocks = max(1, -(-total // (2 * block_tokens)))  # a token has two characters at least, its gap included
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("t"))
    schema = "doc_id long, item_id long, n_tiles int, longest int, tiled int, item_tokens int, coverage double"
    kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.float64()]
    names = [x.split()[0] for x in schema.split(", ")]

    def block(k: int) -> DataFrame:
        items = [tuple(r) for r in bench.filter(F.pmod(F.xxhash64("item_id", "b"), F.lit(blocks)) == k).collect()]
        shared = docs.sparkSession.sparkContext.broadcast(Seeds(items, min_match))

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            seeds, ids = shared.value, WordIds(word_id)
            for batch in batches:
                rows = []
                for i, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                    for item, tiles in seeds.tiles(tokens(text, ids)):
                        n = sum(x[2] for x in tiles)
                        rows.append((i, seeds.ids[item], len(tiles), max(x[2] for x in tiles), n, seeds.sizes[item], n / seeds.sizes[item]))
                yield pa.RecordBatch.from_arrays([pa.array(c, x) for c, x in zip(list(zip(*rows)) or [()] * 7, kinds)], names=names)

        return src.mapInArrow(run, schema)

    out = block(0)
    for k in range(1, blocks):
        out = out.unionByName(block(k))
    return out


COVERAGE = 0.5


def contaminated(docs: DataFrame, benchmark: DataFrame, coverage: float = COVERAGE) -> DataFrame:
    """The pairs of document and item of which at least that share of the item lies under tiles."""
    return overlaps(docs, benchmark).filter(F.col("coverage") >= coverage)


def op4_decontaminate(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    return contaminated(docs, benchmark)
