"""Best-fit packing of token sequences by a grouping genetic algorithm on islands.

A chromosome is a list of bins. Crossover injects whole well-filled bins of one parent
into the other, drops the bins that now hold a document twice, and best-fits what was
displaced. Inside an island several demes evolve and hand their elites round a ring.
Islands are groups of pieces in separate tasks; after each round an island settles its
elite bins, and the pieces of its poorly filled ones migrate to islands drawn anew.

Cases: null and empty texts are one piece of one id (the separator); repeated rows and
repeated ids are packed one by one, since pieces are told apart by a row number written
once; an empty table gives no rows; very long texts are cut, never shortened.
"""

from __future__ import annotations

import bisect
import random
import zlib
from collections.abc import Iterable, Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._shared import durable
from .vocabulary import encoded, encoder

LENGTH = 2048
PIECE = "doc_id long, piece int, start long, length long, ids_crc32 long"


def token_pieces(docs: DataFrame, vocabulary: str = "byte_bpe_50k.json", length: int = LENGTH, separator: int = 0) -> DataFrame:
    """The ids of each text and the separator, cut into pieces of `length`; a shorter one comes first."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows: list[tuple] = []
            for i, ids in zip(batch.column(0).to_pylist(), encoded(vocabulary, batch.column(1).to_pylist(), separator)):
                ids = ids.astype("<u4", copy=False)
                n, at = len(ids), 0
                for k, end in enumerate(range(n % length or length, n + 1, length)):
                    rows.append((i, k, at, end - at, zlib.crc32(ids[at:end])))
                    at = end
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*rows)) or [()] * 5, kinds)], names=["doc_id", "piece", "start", "length", "ids_crc32"])
        encoder(vocabulary).forget()  # the worker lives on, with other stages' memory

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string").alias("t")).mapInArrow(run, PIECE)


# ---- the genetic algorithm: items are numbers into `sizes`, a bin is a tuple of items


class Solution:
    __slots__ = ("bins", "fills")

    def __init__(self, bins: list[list[int]], fills: list[int]):
        self.bins, self.fills = bins, fills

    def fitness(self, cap: int) -> tuple[int, float]:
        """Fewer bins first, then fuller ones."""
        return -len(self.bins), sum((f / cap) ** 2 for f in self.fills)


def best_fit(items: list[int], sizes: list[int], cap: int, bins: list[list[int]], fills: list[int]) -> Solution:
    """Puts each item into the bin that it leaves least room in. Bins and fills are extended in place."""
    by_room: list[list[int]] = [[] for _ in range(cap + 1)]
    mask = 0
    for b, f in enumerate(fills):
        by_room[cap - f].append(b)
        mask |= 1 << (cap - f)
    for i in items:
        s = sizes[i]
        m = mask >> s
        if m:
            room = s + (m & -m).bit_length() - 1
            b = by_room[room].pop()
            if not by_room[room]:
                mask ^= 1 << room
            bins[b].append(i)
            fills[b] += s
        else:
            room, b = cap, len(bins)
            bins.append([i])
            fills.append(s)
        by_room[room - s].append(b)
        mask |= 1 << (room - s)
    return Solution(bins, fills)


def exchange(bins: list[list[int]], fills: list[int], loose: list[int], sizes: list[int], cap: int) -> list[int]:
    """Loose items that fill a bin better change places with one or two of its items; gives the items loose now."""
    loose = sorted(loose, key=lambda i: sizes[i])
    of = [sizes[i] for i in loose]
    for k, items in enumerate(bins):
        if fills[k] == cap or len(items) > 8:  # bins of many small items are best-fitted well already
            continue
        outs = [(sizes[i], (i,)) for i in items] + [(sizes[i] + sizes[j], (i, j)) for x, i in enumerate(items) for j in items[:x]]
        best = (0, 0, ())
        for s, out in outs:
            at = bisect.bisect_right(of, s + cap - fills[k]) - 1
            if at >= 0 and of[at] - s > best[0]:
                best = (of[at] - s, at, out)
        gain, at, out = best
        if gain:
            bins[k] = [i for i in items if i not in out] + [loose.pop(at)]
            of.pop(at)
            fills[k] += gain
            for i in out:
                place = bisect.bisect_left(of, sizes[i])
                of.insert(place, sizes[i])
                loose.insert(place, i)
    return loose


def crossover(a: Solution, b: Solution, sizes: list[int], cap: int, rng: random.Random, share: float) -> Solution:
    """b's well-filled bins go into a; a's bins that hold any of their items go; the displaced are best-fitted."""
    ranked = sorted(range(len(b.bins)), key=lambda k: (-b.fills[k], rng.random()))
    chosen = ranked[: max(1, int(share * len(ranked)))]
    taken = {i for k in chosen for i in b.bins[k]}
    bins, fills, displaced = [list(b.bins[k]) for k in chosen], [b.fills[k] for k in chosen], []
    # the emptiest bins of a are emptied too, and a few others, so that the search does not stand still
    worst = sorted(a.fills)[min(len(a.fills) - 1, max(1, len(a.fills) // 50))]
    for items, fill in zip(a.bins, a.fills):
        if taken.isdisjoint(items) and not (fill < cap and (fill <= worst or rng.random() < 0.05)):
            bins.append(list(items))
            fills.append(fill)
        else:
            displaced += [i for i in items if i not in taken]
    displaced = exchange(bins, fills, displaced, sizes, cap)
    displaced.sort(key=lambda i: (-sizes[i], rng.random()))
    return best_fit(displaced, sizes, cap, bins, fills)


def lower_bound(sizes: list[int], cap: int) -> int:
    return max(-(-sum(sizes) // cap), sum(2 * s > cap for s in sizes))


def evolve(sizes: list[int], cap: int, seed: int, demes: int = 2, each: int = 4, generations: int = 60, every: int = 5, patience: int = 8) -> Solution:
    """The best of all demes. No search where best fit alone needs no more bins than any packing must."""
    rng = random.Random(seed)
    order = sorted(range(len(sizes)), key=lambda i: (-sizes[i], i))
    first = best_fit(order, sizes, cap, [], [])
    least = lower_bound(sizes, cap)
    if len(first.bins) <= least:
        return first
    fit = lambda s: s.fitness(cap)
    blurred = lambda: best_fit(sorted(order, key=lambda i: -sizes[i] * rng.uniform(0.5, 1)), sizes, cap, [], [])
    islands = [[first if k == 0 else blurred() for k in range(each)] for _ in range(demes)]
    best, still = max((s for d in islands for s in d), key=fit), 0
    for g in range(1, generations + 1):
        still += 1
        for d in islands:
            d.sort(key=fit, reverse=True)
            a, b = rng.sample(range(each), 2)
            for one, other in ((a, b), (b, a)):
                child = crossover(d[one], d[other], sizes, cap, rng, rng.uniform(0.1, 0.5))
                last = min(range(each), key=lambda k: fit(d[k]))
                if fit(child) > fit(d[last]):
                    d[last] = child
                if fit(child) > fit(best):
                    best, still = child, 0
        if len(best.bins) <= least or still >= patience:
            break
        if g % every == 0:  # elites go one deme on
            elites = [max(d, key=fit) for d in islands]
            for d, guest in zip(islands, elites[-1:] + elites[:-1]):
                d[min(range(each), key=lambda k: fit(d[k]))] = guest
    return best


def _packer(length: int, slack: int, r: int, last: bool):
    def run(df: pd.DataFrame) -> pd.DataFrame:
        df = df.sort_values("uid", ignore_index=True)
        k = int(df["island"].iloc[0])
        sizes = df["length"].tolist()
        got = evolve(sizes, length, seed=k * 1009 + r)
        seq, off, done = [0] * len(df), [0] * len(df), [False] * len(df)
        for b, (items, fill) in enumerate(zip(got.bins, got.fills)):
            at = 0
            for i in items:
                seq[i], off[i], done[i] = ((r << 24 | k) << 32) | b, at, last or fill >= length - slack
                at += sizes[i]
        return df.drop(columns="island").assign(sequence_id=seq, offset=off, done=done)

    return run


def pack(pieces: DataFrame, length: int = LENGTH, island: int = 4000, rounds: int = 3, slack: int = 2) -> DataFrame:
    """Adds sequence_id and offset to rows of PIECE. Each round has islands of about `island` pieces.

    Bins that lack at most `slack` tokens settle in any round but the last, where all do."""
    numbered = durable(pieces.withColumn("uid", F.monotonically_increasing_id()), "pieces")
    whole = numbered.filter(F.col("length") >= length)
    whole = whole.select("doc_id", "piece", "start", "length", "ids_crc32", (-1 - F.col("uid")).alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    left, settled = numbered.filter(F.col("length") < length), [whole]
    for r in range(rounds):
        n = left.count()
        if not n:
            break
        islands = max(1, -(-n // island))
        last = r == rounds - 1 or islands == 1

        schema = PIECE + ", uid long, sequence_id long, offset long, done boolean"
        dealt = left.select("doc_id", "piece", "start", "length", "ids_crc32", "uid", F.pmod(F.xxhash64(F.lit(r), "uid"), F.lit(islands)).alias("island"))
        got = durable(dealt.groupBy("island").applyInPandas(_packer(length, slack, r, last), schema), f"packed{r}")
        settled.append(got.filter("done").drop("uid", "done"))
        if last:
            break
        left = got.filter("not done").select("doc_id", "piece", "start", "length", "ids_crc32", "uid")
    out = settled[0]
    for x in settled[1:]:
        out = out.unionByName(x)
    return out


def op5_packing(docs: DataFrame) -> DataFrame:
    return pack(token_pieces(docs))
