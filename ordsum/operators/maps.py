"""The ordered map: unique keys in key-contiguous blocks, with a summary per block.

`rows` has columns k (any orderable type, a struct for composite keys), v and block. Block
bounds are explicit splitters, so a row's block never depends on how Spark deals it out.
Maps are immutable: every operation gives a new map over the same or new rows. A map built with
h="all" keeps every entry of a repeated key (`many`); equal keys then lie in one block, by value.

The number of blocks is bounded by `MOST_BLOCKS`; the block table is therefore small by
construction and may be broadcast, collected or windowed whole.

A map that was read from a store (`ordsum.sources.store`) has a `Backing`: the table of its
blocks with their stored summaries, and a reader of single blocks. Summaries, ranks,
positions, slices and filters through summaries then read that table and open the blocks
that a bound cuts, nothing else. A map without one computes the same from its rows.
"""

from __future__ import annotations

import math
from bisect import bisect_right
from collections.abc import Callable
from dataclasses import dataclass, field, replace
from functools import reduce
from itertools import accumulate

from pyspark.sql import Column, DataFrame, Row
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W
from pyspark.sql.internal import InternalFunction

from ordsum.functions.monoids import Monoid

MOST_BLOCKS = 1 << 16
Base = Callable[[Column, Column], Column]
Conflict = Callable[[Column, Column], Column]


def lit_key(value) -> Column:
    """A key as a literal; rows become structs."""
    if isinstance(value, Row):
        return F.struct(*[lit_key(x).alias(n) for n, x in zip(value.__fields__, value)])
    return F.lit(value)


def _whole(x) -> bool:
    return isinstance(x, int) and not isinstance(x, bool)


def _sorted_array(splitters: list) -> tuple[Column, str] | None:
    """Whole numbers, or rows of them, as one constant array and the type that keys take beside it."""
    if all(map(_whole, splitters)):
        # one text, folded to an array once: thousands of literals would be analysed anew with each step of a plan
        return F.split(F.lit(",".join(map(str, splitters))), ",").cast("array<bigint>"), "bigint"
    if all(isinstance(x, Row) and all(map(_whole, x)) for x in splitters):
        kind = "struct<" + ",".join(f"c{i}:bigint" for i in range(len(splitters[0]))) + ">"
        rows = ("named_struct(" + ",".join(f"'c{i}',{x}L" for i, x in enumerate(r)) + ")" for r in splitters)
        return F.expr("array(" + ",".join(rows) + ")"), kind
    return None


def block_of(k: Column, splitters: list) -> Column:
    """How many splitters are at or below the key: a binary search in generated code for whole
    numbers; for other types two steps of about 64 comparisons. A null key falls into block 0."""
    if not splitters:
        return F.lit(0)
    known = _sorted_array(splitters)
    if known is not None:
        at = InternalFunction.array_binary_search(known[0], k.cast(known[1]))
        return F.coalesce(F.greatest(at + 1, -1 - at), F.lit(0))
    step = max(1, int(len(splitters) ** 0.5))
    coarse, fine = splitters[::step], [splitters[i : i + step] for i in range(0, len(splitters), step)]
    pad = lambda xs: F.array(*[lit_key(x) for x in xs])
    at = F.size(F.filter(pad(coarse), lambda s: s <= k))
    inner = F.element_at(F.array(*[pad(xs) for xs in fine]), F.greatest(at, F.lit(1)))
    return F.when(at == 0, F.lit(0)).otherwise((at - 1) * step + F.size(F.filter(inner, lambda s: s <= k))).cast("int")


@dataclass(frozen=True)
class Layout:
    """How keys are cut into blocks: by count, by fan-out, by fill or by a hash priority of keys.

    A map of fewer than `min_parallel_rows` rows is kept in one partition: no work is dealt out for it."""

    policy: str = "count"
    block_rows: int = 4096
    fanout: int = 16
    min_parallel_rows: int = 0

    def wanted(self, n: int) -> int:
        """How many blocks n rows make."""
        if self.policy == "fill":
            return max(1, -(-n // max(1, self.block_rows * 3 // 4)))
        want = max(1, -(-n // self.block_rows))
        return self.fanout ** max(0, round(math.log(want, self.fanout))) if self.policy == "fanout" and want > 1 else want

    def opens(self, n: int) -> Column:
        """Under the priority policy: whether key k begins a block, by its own hash alone, so that equal
        contents give equal blocks whatever came before. The rate halves where blocks would be too many."""
        every = self.block_rows
        while n > every * MOST_BLOCKS // 2:
            every *= 2
        return F.pmod(F.xxhash64("k"), F.lit(every)) == 0

    def sizes(self) -> tuple[int, int]:
        """A block of a stored map is split above the second of these and joined to a neighbour below the first."""
        return self.block_rows // 2, 2 * self.block_rows

    def splitters(self, keys: DataFrame, n: int | None = None) -> list:
        """keys: column k; a repeated key weighs as much as it has rows, if it was counted (column c).
        Answers don't depend on the choice; sizes do."""
        n = keys.count() if n is None else n
        if self.policy == "priority":
            return sorted({r.k for r in keys.filter(self.opens(n)).collect()}) if n > self.block_rows else []
        want = min(MOST_BLOCKS, self.wanted(n))
        if want == 1:
            return []
        # a bounded sample of keys in hash order; quantiles of it are the bounds. Each task would send the driver as many keys
        # as are wanted in all, so only those under a share of the hashes take part; if these are too few, a larger share
        most = min(n, max(32 * min(want, 4096), 8 * want))
        share, kept = 2 * most / n, []
        while True:
            near = keys if share >= 1 else keys.filter(F.xxhash64("k") < int((2 * share - 1) * (1 << 63)))
            kept = near.orderBy(F.xxhash64("k")).limit(most).collect()
            if len(kept) == most or share >= 1:
                break
            share *= max(4, 2 * most / max(1, len(kept)))
        sample = sorted((r.k, r.c if "c" in keys.columns else 1) for r in kept)
        ends = list(accumulate(c for _, c in sample))
        return sorted({sample[bisect_right(ends, ends[-1] * i // want)][0] for i in range(1, want)})


@dataclass(frozen=True)
class Backing:
    """A stored map's blocks. infos and table: block, cut (the splitter it begins at), lo, lov, hi, hiv, n, a, file; in key order."""

    infos: list
    table: DataFrame
    open: Callable[[list], DataFrame]  # block numbers -> k, v, block
    summed: bool = True  # whether `a` belongs to this map's monoid

    def between(self, lo, hi, bounds: str) -> tuple[list, list]:
        """Blocks that lie inside the bounds, and those that a bound cuts. None is no bound."""
        whole, cut = [], []
        for r in self.infos:
            if not r.n or lo is not None and (r.hi < lo or r.hi == lo and bounds[0] == "(") or hi is not None and (r.lo > hi or r.lo == hi and bounds[1] == ")"):
                continue
            left = lo is None or r.lo > lo or r.lo == lo and bounds[0] == "["
            right = hi is None or r.hi < hi or r.hi == hi and bounds[1] == "]"
            (whole if left and right else cut).append(r.block)
        return whole, cut


def _within(lo, hi, bounds: str) -> Column:
    k, ok = F.col("k"), F.lit(True)
    if lo is not None:
        ok = ok & (k >= lit_key(lo) if bounds[0] == "[" else k > lit_key(lo))
    if hi is not None:
        ok = ok & (k <= lit_key(hi) if bounds[1] == "]" else k < lit_key(hi))
    return ok


def _dedup(df: DataFrame, h: Conflict | None, tie: list[Column], monoid_sum: bool) -> DataFrame:
    if h is None:
        first = F.min_by("v", F.struct(*tie)) if tie else F.min("v")
        return df.groupBy("k").agg(first.alias("v"))
    rows = F.transform(F.array_sort(F.collect_list(F.struct(*tie, F.col("v").alias("__v")))), lambda x: x["__v"])
    tail = F.slice(rows, F.lit(2), F.greatest(F.size(rows), F.lit(1)))
    return df.groupBy("k").agg(F.aggregate(tail, F.element_at(rows, 1), lambda s, x: h(s, x)).alias("v"))


@dataclass(frozen=True)
class SummaryMap:
    rows: DataFrame
    splitters: list
    monoid: Monoid | None = None
    base: Base = field(default=lambda k, v: v)
    layout: Layout = Layout()
    stored: Backing | None = None
    many: bool = False  # whether a key may have several entries

    # ---- building

    @staticmethod
    def build(df: DataFrame, key: Column | str, value: Column | str, monoid: Monoid | None = None, base: Base | None = None, h: Conflict | str | None = None, tie: list | None = None, layout: Layout = Layout(), null_keys: str = "error") -> "SummaryMap":
        """From a sequence with repeated keys. h: None keeps the first by `tie` (the least value where there is none),
        "sum" adds, "all" keeps every entry, a function folds in tie order."""
        key, value = (F.col(x) if isinstance(x, str) else x for x in (key, value))
        tie = [F.col(x) if isinstance(x, str) else x for x in tie or []]
        names = [f"__t{i}" for i in range(len(tie))]
        src = df.select(key.alias("k"), value.alias("v"), *[t.alias(n) for t, n in zip(tie, names)])
        kind = src.schema["k"].dataType
        if isinstance(kind, (T.MapType, T.VariantType, T.CalendarIntervalType)):
            raise ValueError(f"keys of type {kind.simpleString()} have no order")
        if null_keys == "drop":
            src = src.filter(F.col("k").isNotNull())
        else:
            src = src.withColumn("k", F.when(F.col("k").isNull(), F.raise_error(F.lit("null key"))).otherwise(F.col("k")))
        if isinstance(kind, (T.DoubleType, T.FloatType)):
            src = src.withColumn("k", F.col("k") + F.lit(0.0).cast(kind))  # -0.0 is 0.0
        if h == "all":
            unique = src.select("k", "v")
        else:
            unique = src.groupBy("k").agg(F.sum("v").cast(src.schema["v"].dataType).alias("v")) if h == "sum" else _dedup(src, h, [F.col(n) for n in names], False)
        n = unique.count()
        splitters = layout.splitters(unique.groupBy("k").agg(F.count("*").alias("c")) if h == "all" else unique.select("k"), n)
        unique = unique.coalesce(1) if n < layout.min_parallel_rows else unique
        return SummaryMap(unique.withColumn("block", block_of(F.col("k"), splitters)), splitters, monoid, base or (lambda k, v: v), layout, many=h == "all")

    @staticmethod
    def empty(spark, schema: str = "k bigint, v bigint", monoid: Monoid | None = None) -> "SummaryMap":
        return SummaryMap(spark.createDataFrame([], schema).withColumn("block", F.lit(0)), [], monoid)

    @staticmethod
    def singleton(spark, k, v, monoid: Monoid | None = None) -> "SummaryMap":
        return SummaryMap(spark.range(1).select(lit_key(k).alias("k"), F.lit(v).alias("v"), F.lit(0).alias("block")), [], monoid)

    @staticmethod
    def single(row: DataFrame, monoid: Monoid | None = None) -> "SummaryMap":
        """The map of the only row (k, v) of a table."""
        return SummaryMap(row.select("k", "v", F.lit(0).alias("block")), [], monoid)

    def with_rows(self, rows: DataFrame) -> "SummaryMap":
        return self._over(rows.select("k", "v", block_of(F.col("k"), self.splitters).alias("block")))

    def _over(self, rows: DataFrame) -> "SummaryMap":
        """The same kind of map over other rows."""
        return replace(self, rows=rows, stored=None)

    def opened(self, blocks: list) -> DataFrame:
        """The rows of some blocks; of a stored map only their files are read."""
        if self.stored is not None:
            return self.stored.open(blocks)
        return self.rows.filter(F.col("block").isin(blocks) if blocks else F.lit(False))

    def _place(self, k) -> int:
        return bisect_right(self.splitters, k)

    def entries(self, ordered: bool = False) -> DataFrame:
        out = self.rows.select("k", "v")
        return out.orderBy("k") if ordered else out

    def domain(self) -> DataFrame:
        return self.rows.select("k")

    # ---- summaries

    def _a(self) -> Column:
        return self.base(F.col("k"), F.col("v")).cast(self.monoid.dtype)

    def _summed(self) -> bool:
        return self.stored is not None and self.stored.summed

    def block_table(self) -> DataFrame:
        """(block, lo, hi, n, a): one small row per block; stored, or by partial aggregation."""
        if self.stored is not None and (self.monoid is None or self.stored.summed):
            return self.stored.table.filter("n > 0").select("block", "lo", "hi", "n", *(["a"] if self.monoid else []))
        a = [self.monoid.fold(F.col("k"), self._a()).alias("a")] if self.monoid else []
        return self.rows.groupBy("block").agg(F.min("k").alias("lo"), F.max("k").alias("hi"), F.count("*").alias("n"), *a)

    def pyramid(self) -> DataFrame:
        """(level, node, a): partial sums of F^level blocks each, level 0 the blocks."""
        level = self.block_table().select(F.lit(0).alias("level"), F.col("block").cast("bigint").alias("node"), "a")
        out, nodes, depth = level, len(self.splitters) + 1, 0
        while nodes > 1:
            depth, nodes = depth + 1, -(-nodes // self.layout.fanout)
            up = F.floor(F.col("node") / self.layout.fanout).cast("bigint")
            level = level.groupBy(up.alias("up")).agg(self.monoid.fold(F.col("node"), F.col("a")).alias("a")).select(F.lit(depth).alias("level"), F.col("up").alias("node"), "a")
            out = out.unionByName(level)
        return out

    def summary(self) -> DataFrame:
        """One row (a): the whole map, the identity if it is empty. Folds block summaries."""
        return self._fold_blocks(self.block_table())

    def _fold_blocks(self, blocks: DataFrame) -> DataFrame:
        return blocks.agg(self.monoid.fold(F.col("block"), F.col("a")).alias("a"))

    def _parts(self, lo, hi, bounds: str) -> DataFrame:
        """(block, a) of what lies in the bounds: stored summaries of whole blocks, folds of the rows of cut ones."""
        if not self._summed():
            return self.range(lo, hi, bounds).block_table().select("block", "a")
        whole, cut = self.stored.between(lo, hi, bounds)
        out = self.stored.table.filter(F.col("block").between(whole[0], whole[-1]) & (F.col("n") > 0) if whole else F.lit(False)).select("block", "a")
        if cut:
            rows = self.stored.open(cut).filter(_within(lo, hi, bounds))
            out = out.unionByName(rows.groupBy("block").agg(self.monoid.fold(F.col("k"), self._a()).alias("a")))
        return out

    def summary_left(self, k, inclusive: bool = True) -> DataFrame:
        return self._fold_blocks(self._parts(None, k, "[]" if inclusive else "[)"))

    def summary_right(self, k, inclusive: bool = True) -> DataFrame:
        return self._fold_blocks(self._parts(k, None, "[]" if inclusive else "(]"))

    def summary_range(self, lo, hi, bounds: str = "[]") -> DataFrame:
        return self._fold_blocks(self._parts(lo, hi, bounds))

    def summary_filter(self, h: Callable[[Column], Column], all_h: Callable[[Column], Column] | None = None) -> "SummaryMap":
        """Rows whose own summary satisfies h, from blocks whose summary does.

        h must pass through the combine (`check_or_homomorphic`). Blocks on which all_h holds
        are taken whole. Of a stored map only the blocks that satisfy h are read."""
        keep = self.block_table().filter(h(F.col("a"))).select("block", (all_h(F.col("a")) if all_h else F.lit(False)).alias("whole"))
        if not self._summed():  # nothing is stored that could spare a row: one pass over them
            return self._over(self.rows.filter(h(self._a())))
        found = keep.collect()  # bounded by the number of blocks
        rows = self.stored.open([r.block for r in found if not r.whole]).filter(h(self._a()))
        whole = [r.block for r in found if r.whole]
        return self._over(rows.unionByName(self.stored.open(whole)) if whole else rows)

    def summary_project(self, g: Callable[[Column], Column], m2: Monoid, lo, hi) -> DataFrame:
        """g of the range's summary, without combining the big summaries: g of each part first, then m2."""
        return self._parts(lo, hi, "[]").agg(m2.fold(F.col("block"), g(F.col("a"))).alias("a"))

    # ---- points and slices

    def size(self) -> DataFrame:
        if self.stored is not None:
            return self.stored.table.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))
        return self.rows.agg(F.count("*").alias("n"))

    def find(self, k) -> DataFrame:
        return self.opened([self._place(k)]).filter(F.col("k") == lit_key(k)).select("k", "v")

    def _near(self, blocks: list) -> DataFrame:
        """Rows of the first block of the list that has any (and of an earlier one that may have the answer)."""
        return self.stored.open(blocks) if self.stored is not None else self.rows

    def first(self) -> DataFrame:
        """The entry of the least key; where keys have several entries, all of that key's."""
        if self.many:
            return self._ends(F.min, self._filled()[:1])
        return self._near(self._filled()[:1]).orderBy("k").limit(1).select("k", "v")

    def last(self) -> DataFrame:
        if self.many:
            return self._ends(F.max, self._filled()[-1:])
        return self._near(self._filled()[-1:]).orderBy(F.desc("k")).limit(1).select("k", "v")

    def _ends(self, f, blocks: list) -> DataFrame:
        rows = self._near(blocks)
        return rows.join(F.broadcast(rows.agg(f("k").alias("k"))), "k", "left_semi").select("k", "v")

    def _filled(self) -> list:
        return [r.block for r in self.stored.infos if r.n] if self.stored is not None else []

    def next(self, k) -> DataFrame:
        """Opens one block: that of the first stored greatest key above k."""
        at = [r.block for r in self.stored.infos if r.n and r.hi > k][:1] if self.stored is not None else []
        return self._near(at).filter(F.col("k") > lit_key(k)).orderBy("k").limit(1).select("k", "v")

    def prev(self, k) -> DataFrame:
        at = [r.block for r in self.stored.infos if r.n and r.lo < k][-1:] if self.stored is not None else []
        return self._near(at).filter(F.col("k") < lit_key(k)).orderBy(F.desc("k")).limit(1).select("k", "v")

    def rank(self, k) -> DataFrame:
        """How many keys are smaller."""
        if self.stored is None:
            return self.rows.agg(F.count(F.when(F.col("k") < lit_key(k), 1)).alias("r"))
        whole, cut = self.stored.between(None, k, "[)")
        before = sum(r.n for r in self.stored.infos[: max(whole, default=-1) + 1])
        return self.stored.open(cut).filter(F.col("k") < lit_key(k)).agg((F.count("*") + F.lit(before)).alias("r"))

    def ranked(self) -> DataFrame:
        """(k, v, block, r): 0-based ranks from block counts and a window inside each block."""
        counts = self.block_table().select("block", "n")
        # at most MOST_BLOCKS rows
        before = counts.select("block", (F.sum("n").over(W.orderBy("block").partitionBy(F.lit(0))) - F.col("n")).alias("before"))
        inside = F.row_number().over(W.partitionBy("block").orderBy("k", *(["v"] if self.many else []))) - 1
        return self.rows.withColumn("__r", inside).join(F.broadcast(before), "block").select("k", "v", "block", (F.col("before") + F.col("__r")).alias("r"))

    def select(self, i: int) -> DataFrame:
        if self.stored is None:
            return self.ranked().filter(F.col("r") == i).select("k", "v")
        for r in self.stored.infos:
            if 0 <= i < r.n:
                return self.stored.open([r.block]).orderBy("k", *(["v"] if self.many else [])).offset(i).limit(1).select("k", "v")
            i -= r.n
        return self.stored.open([]).select("k", "v")

    def up_to(self, k, inclusive: bool = True) -> "SummaryMap":
        return self.range(None, k, "[]" if inclusive else "[)")

    def down_to(self, k, inclusive: bool = True) -> "SummaryMap":
        return self.range(k, None, "[]" if inclusive else "(]")

    def range(self, lo, hi, bounds: str = "[]") -> "SummaryMap":
        """Entries between the bounds; None is no bound. Of a stored map only blocks that reach into them are read."""
        if self.stored is not None:
            whole, cut = self.stored.between(lo, hi, bounds)
            return self._over(self.stored.open(sorted(whole + cut)).filter(_within(lo, hi, bounds)))
        near = F.lit(True)
        if lo is not None:
            near = near & (F.col("block") >= self._place(lo))
        if hi is not None:
            near = near & (F.col("block") <= self._place(hi))
        return self._over(self.rows.filter(near & _within(lo, hi, bounds)))

    def split(self, k) -> tuple["SummaryMap", DataFrame, "SummaryMap"]:
        return self.up_to(k, False), self.find(k), self.down_to(k, False)

    def decompose(self) -> tuple["SummaryMap", DataFrame, "SummaryMap"]:
        """Left half, middle entry, right half: what a tree's root would give."""
        n = self.size().first().n
        mid = self.select(n // 2)
        k = mid.first().k
        return self.up_to(k, False), mid, self.down_to(k, False)

    # ---- updates and algebra

    def _one(self, k, v) -> DataFrame:
        kinds = self.rows.schema
        return self.rows.sparkSession.range(1).select(lit_key(k).cast(kinds["k"].dataType).alias("k"), F.lit(v).cast(kinds["v"].dataType).alias("v"))

    def _beside(self, blocks: list) -> DataFrame:
        """All rows but those of some blocks."""
        if self.stored is not None:
            there = set(blocks)
            return self.stored.open([r.block for r in self.stored.infos if r.block not in there])
        return self.rows.filter(~F.col("block").isin(blocks))

    def insert(self, k, v, h: Conflict | None = None) -> "SummaryMap":
        """One entry: only its block is joined, the others pass by."""
        at = [self._place(k)]
        return self.with_rows(self._beside(at).select("k", "v").unionByName(_merged(self.opened(at), self._one(k, v), h, self.many)))

    def delete(self, k) -> "SummaryMap":
        return self._over(self.rows.filter(F.col("k") != lit_key(k)))

    def insert_many(self, batch: DataFrame, h: Conflict | None = None) -> "SummaryMap":
        """Rows of `batch` (k, v; unique) over the map's: the new value wins, or h(old, new). Where keys have
        several entries, those of the batch come beside the map's.

        Of a stored map the blocks that the batch touches are merged; if these are fewer than half, the others
        are only passed on, unsorted and unshuffled."""
        if self.stored is not None:
            touched = self.touched(batch)
            if 2 * len(touched) <= len(self.stored.infos):
                return self.with_rows(self._beside(touched).select("k", "v").unionByName(_merged(self.opened(touched), batch, h, self.many)))
        return self.with_rows(_merged(self.rows, batch, h, self.many))

    def touched(self, keys: DataFrame) -> list:
        """Blocks that the keys fall in; at most as many numbers as there are blocks."""
        return sorted(r.b for r in keys.select(block_of(F.col("k").cast(self.rows.schema["k"].dataType), self.splitters).alias("b")).distinct().collect())

    def delete_many(self, keys: DataFrame) -> "SummaryMap":
        return self._over(self.rows.join(keys.select("k"), "k", "left_anti").select("k", "v", "block"))

    def filter(self, pred: Callable[[Column, Column], Column]) -> "SummaryMap":
        return self._over(self.rows.filter(pred(F.col("k"), F.col("v"))))

    def map_values(self, fn: Base) -> "SummaryMap":
        return self._over(self.rows.select("k", fn(F.col("k"), F.col("v")).alias("v"), "block"))

    def map_reduce(self, base: Base, monoid: Monoid) -> DataFrame:
        return replace(self, base=base, monoid=monoid, stored=None).summary()

    def reduce_values(self, monoid: Monoid) -> DataFrame:
        return self.map_reduce(lambda k, v: v, monoid)


def _merged(rows: DataFrame, batch: DataFrame, h: Conflict | None, many: bool = False) -> DataFrame:
    if many:
        if h is not None:
            raise ValueError("keys of several entries have no conflict to resolve")
        return rows.select("k", "v").unionByName(batch.select("k", "v"))
    b = batch.select("k", F.col("v").alias("w"), F.lit(True).alias("there"))
    both = rows.select("k", "v", F.lit(True).alias("here")).join(b, "k", "full_outer")
    return both.select("k", _meet("here", "there", "v", "w", h or (lambda old, new: new)))


def _meet(here: str, there: str, v: str, w: str, h: Conflict) -> Column:
    return F.when(F.col(here).isNull(), F.col(w)).when(F.col(there).isNull(), F.col(v)).otherwise(h(F.col(v), F.col(w))).alias("v")


def union(a: SummaryMap, b: SummaryMap, h: Conflict | None = None) -> SummaryMap:
    """Keys of either. The left value wins, or h(left, right). The result is a map of a's kind, cut as the finer of the two.
    If a keeps several entries of a key, all of both stay."""
    if a.many:
        return a.insert_many(b.entries(), h)
    if a.stored is None and len(b.splitters) > len(a.splitters):
        return replace(a, splitters=b.splitters).with_rows(_merged(a.rows, b.entries(), h or (lambda left, right: left)))
    return a.insert_many(b.entries(), h or (lambda left, right: left))


def union_commutative(a: SummaryMap, b: SummaryMap, monoid: Monoid) -> SummaryMap:
    """For a commutative h one aggregation is enough."""
    rows = a.entries().unionByName(b.entries()).groupBy("k").agg(monoid.total(F.col("v")).alias("v"))
    return a.with_rows(rows)


def intersect(a: SummaryMap, b: SummaryMap, h: Conflict | None = None) -> SummaryMap:
    if h is None:
        return a._over(a.rows.join(b.rows.select("k"), "k", "left_semi").select("k", "v", "block"))
    both = a.rows.join(b.rows.select("k", F.col("v").alias("w")), "k")
    return a._over(both.select("k", h(F.col("v"), F.col("w")).alias("v"), "block"))


def difference(a: SummaryMap, b: SummaryMap) -> SummaryMap:
    return a.delete_many(b.domain())


def _edge(m: SummaryMap, f) -> object:
    return m.block_table().agg(f("hi" if f is F.max else "lo").alias("e")).first().e


def link(left: SummaryMap, k, v, right: SummaryMap) -> SummaryMap:
    """left, one entry, right; keys must lie in that order."""
    hi, lo = _edge(left, F.max), _edge(right, F.min)
    if hi is not None and not hi < k or lo is not None and not k < lo:
        raise ValueError("keys of the linked maps must lie on either side of the middle key")
    one = SummaryMap.singleton(left.rows.sparkSession, k, v).rows
    return _beside(left, right, one)


def concat(left: SummaryMap, right: SummaryMap) -> SummaryMap:
    hi, lo = _edge(left, F.max), _edge(right, F.min)
    if hi is not None and lo is not None and not hi < lo:
        raise ValueError("the left map's keys must lie below the right map's")
    return _beside(left, right, None)


def _beside(left: SummaryMap, right: SummaryMap, middle: DataFrame | None) -> SummaryMap:
    rows = left.entries().unionByName(right.entries())
    if middle is not None:
        rows = rows.unionByName(middle.select(F.col("k").cast(left.rows.schema["k"].dataType).alias("k"), F.col("v").cast(left.rows.schema["v"].dataType).alias("v")))
    cuts = sorted({*left.splitters, *right.splitters})
    cuts = cuts[:: -(-len(cuts) // (MOST_BLOCKS - 1)) or 1]  # thinned evenly where they are too many
    return replace(left, splitters=cuts).with_rows(rows)


def build_by_unions(parts: list[SummaryMap], h: Conflict | None = None) -> SummaryMap:
    """Divide and conquer: maps of parts, united pairwise. Kept beside the sort-based build for comparison."""
    while len(parts) > 1:
        parts = [union(parts[i], parts[i + 1], h) if i + 1 < len(parts) else parts[i] for i in range(0, len(parts), 2)]
    return reduce(lambda a, b: a, parts)
