"""Many queries at once, as joins: finds, neighbours, ranks, prefixes, ranges, range summaries."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W
from pyspark.sql import WindowSpec

from ordsum.operators.maps import SummaryMap, block_of
from ordsum.plans.choose import SMALL_BATCH, choose, windowable

HUGE = "unbounded"


def find_many(m: SummaryMap, q: DataFrame) -> DataFrame:
    """q: k. (k, v) of each probe, v null where the key is absent."""
    probes = q.select("k", block_of(F.col("k"), m.splitters).alias("block"))
    return probes.join(m.rows, ["block", "k"], "left").select("k", "v")


def _carry(m: SummaryMap) -> DataFrame:
    """Per block what lies before and after it, from the stored block table where there is one. The table has a bounded number of rows."""
    spark = m.rows.sparkSession
    every = spark.range(len(m.splitters) + 1).select(F.col("id").cast("int").alias("block"))
    summed = m.monoid is not None and m.monoid.agg is not None
    if m.stored is not None and (m.stored.summed or not summed):
        end = lambda k, v: F.when(F.col("n") > 0, F.struct(F.col(k).alias("k"), F.col(v).alias("v")))
        t = m.stored.table.select("block", F.when(F.col("n") > 0, F.col("n")).alias("n"), end("hi", "hiv").alias("last"), end("lo", "lov").alias("first"), "a")
    else:
        e = F.struct("k", "v")
        parts = [F.count("*").alias("n"), F.max_by(e, "k").alias("last"), F.min_by(e, "k").alias("first")]
        t = m.rows.groupBy("block").agg(*parts, *([m.monoid.agg(m._a()).alias("a")] if summed else []))
    t = every.join(t, "block", "left")
    # what comes after is what came before in the other order: a frame that ends behind is folded anew for each row
    before, after = (W.partitionBy(F.lit(0)).orderBy(o).rowsBetween(W.unboundedPreceding, -1) for o in ("block", F.desc("block")))
    out = [F.coalesce(F.sum("n").over(before), F.lit(0)).alias("cn"), F.last("last", True).over(before).alias("cp"), F.last("first", True).over(after).alias("cf")]
    if summed:
        out.append(m.monoid.agg(F.col("a")).over(before).alias("ca"))
    return t.select("block", *out)


def _sides() -> tuple[WindowSpec, WindowSpec]:
    """Frames inside a block: what lies at or before a row, and what lies at or after it. Both run from their order's
    beginning, so that each is one pass; the one that no column asks for is not sorted."""
    orders = ("k", "tag"), (F.desc("k"), F.desc("tag"))
    past, coming = (W.partitionBy("block").orderBy(*o).rowsBetween(W.unboundedPreceding, 0) for o in orders)
    return past, coming


def asof(m: SummaryMap, points: DataFrame) -> DataFrame:
    """points: qid, k, tag (0: what is below k, 2: what is at or below it).

    Gives (qid, k, tag, n, a, prev, next): how many entries come before, their summary,
    the entry before and the entry after. One sorted pass inside blocks plus carries."""
    summed = m.monoid is not None and m.monoid.agg is not None
    none = F.lit(None)
    entry = m.rows.select("block", "k", F.lit(1).alias("tag"), none.cast("bigint").alias("qid"), F.struct("k", "v").alias("e"), *([m._a().alias("x")] if summed else []))
    kind = m.rows.schema["k"].dataType
    asked = points.select(block_of(F.col("k").cast(kind), m.splitters).alias("block"), F.col("k").cast(kind).alias("k"), F.col("tag").cast("int").alias("tag"), F.col("qid").cast("bigint").alias("qid"),
                          none.cast(entry.schema["e"].dataType).alias("e"), *([none.cast(m.monoid.dtype).alias("x")] if summed else []))
    past, coming = _sides()
    cols = [F.count("e").over(past).alias("n"), F.last("e", True).over(past).alias("p"), F.last("e", True).over(coming).alias("f")]
    if summed:
        cols.append(m.monoid.agg(F.col("x")).over(past).alias("a"))
    got = entry.unionByName(asked).select("block", "k", "tag", "qid", *cols).filter("qid is not null").join(F.broadcast(_carry(m)), "block")
    out = [(F.col("n") + F.col("cn")).alias("n"), F.coalesce("p", "cp").alias("prev"), F.coalesce("f", "cf").alias("next")]
    if summed:
        both = m.monoid.combine2(F.coalesce("ca", m.monoid.neutral()), F.coalesce("a", m.monoid.neutral()))
        out.append(both.alias("a"))
    return got.select("qid", "k", "tag", *out)


def neighbor_many(m: SummaryMap, q: DataFrame, side: str) -> DataFrame:
    """q: qid, k. The entry strictly before or after: (qid, k, nk, nv), null where there is none. Equal keys are asked once."""
    e = "next" if side == "next" else "prev"
    found = asof(m, q.select("k").distinct().select(F.lit(0).alias("qid"), "k", F.lit(2 if side == "next" else 0).alias("tag")))
    found = found.select(F.col("k").alias("__k"), F.col(e)["k"].alias("nk"), F.col(e)["v"].alias("nv"))
    return q.select("qid", "k").join(found, F.col("k") == F.col("__k")).select("qid", "k", "nk", "nv")


def rank_many(m: SummaryMap, q: DataFrame) -> DataFrame:
    return asof(m, q.withColumn("tag", F.lit(0))).select("qid", "k", F.col("n").alias("r"))


def select_many(m: SummaryMap, q: DataFrame) -> DataFrame:
    """q: i. Entries by 0-based position."""
    return q.select("i").join(m.ranked(), F.col("i") == F.col("r"), "left").select("i", "k", "v")


def summary_left_many(m: SummaryMap, q: DataFrame, inclusive: bool = True) -> DataFrame:
    return asof(m, q.withColumn("tag", F.lit(2 if inclusive else 0))).select("qid", "k", "a")


# ---- ranges


def _located(m: SummaryMap, q: DataFrame) -> DataFrame:
    return q.withColumns({"bl": block_of(F.col("lo"), m.splitters), "br": block_of(F.col("hi"), m.splitters)}).filter("lo <= hi")


def range_many(m: SummaryMap, q: DataFrame) -> DataFrame:
    """q: qid, lo, hi (closed). All entries of each range: an equi-join on block, then a check of the bounds."""
    spread = _located(m, q).select("qid", "lo", "hi", F.explode(F.sequence("bl", "br")).alias("block"))
    # exploded rows are many more than their estimate, so they are never broadcast
    return spread.hint("merge").join(m.rows, "block").filter("k between lo and hi").select("qid", "k", "v")


def cover(a: Column, b: Column, fanout: int, levels: int) -> Column:
    """Array of (level, node): the fewest pyramid nodes whose blocks are exactly a..b; empty if a > b."""

    def seq(x: Column, y: Column, level: int) -> Column:
        nodes = F.when(x <= y, F.sequence(x, y)).otherwise(F.array().cast("array<bigint>"))
        return F.transform(nodes, lambda n: F.struct(F.lit(level).alias("level"), n.alias("node")))

    parts = []
    up = lambda level: (F.ceil(a / F.lit(fanout**level)).cast("bigint"), F.floor((b + 1) / F.lit(fanout**level)).cast("bigint"))
    for level in range(levels + 1):
        lo, hi = up(level)
        lo1, hi1 = up(level + 1)
        inner = lo1 < hi1
        first = seq(lo, F.when(inner & (F.lit(level) < levels), F.least(lo1 * fanout - 1, hi - 1)).otherwise(hi - 1), level)
        second = seq(F.when(inner & (F.lit(level) < levels), hi1 * fanout).otherwise(hi), hi - 1, level)
        parts.append(F.when(lo < hi, F.concat(first, second)).otherwise(F.array().cast("array<struct<level:int,node:bigint>>")))
    return F.concat(*parts)


def _depth(m: SummaryMap) -> int:
    depth, n = 0, len(m.splitters) + 1
    while n > 1:
        n, depth = -(-n // m.layout.fanout), depth + 1
    return depth


def _boundaries(m: SummaryMap, q: DataFrame) -> DataFrame:
    """(qid, pos, a): folds of the rows of a range in its first and last block.

    Where the monoid has an aggregate, one sorted pass inside each block gives what lies from each lower
    bound on and up to each upper one; only ranges inside a single block are joined with its rows."""
    near = q
    if windowable(m.monoid):
        kind, none = m.rows.schema["k"].dataType, F.lit(None)
        end = lambda block, k, tag: F.struct(F.col(block).cast("int").alias("block"), F.col(k).cast(kind).alias("k"), F.lit(tag).alias("tag"))
        asked = q.filter("bl <> br").select("qid", F.explode(F.array(end("bl", "lo", 0), end("br", "hi", 2))).alias("e")).select("e.block", "e.k", "e.tag", F.col("qid").cast("bigint").alias("qid"), none.cast(m.monoid.dtype).alias("x"))
        entry = m.rows.select(F.col("block").cast("int").alias("block"), "k", F.lit(1).alias("tag"), none.cast("bigint").alias("qid"), m._a().alias("x"))
        upto, on = (m.monoid.agg(F.col("x")).over(side) for side in _sides())
        ends = entry.unionByName(asked).select("qid", "block", "tag", upto.alias("upto"), on.alias("on")).filter("qid is not null")
        ends = ends.select("qid", F.col("block").cast("bigint").alias("pos"), F.coalesce(F.when(F.col("tag") == 2, F.col("upto")).otherwise(F.col("on")), m.monoid.neutral()).alias("a"))
        near = q.filter("bl = br")
    single = near.select("qid", "lo", "hi", F.explode(F.array_distinct(F.array("bl", "br"))).alias("block"))
    rows = single.join(m.rows, "block").filter("k between lo and hi")
    part = rows.groupBy("qid", F.col("block").cast("bigint").alias("pos")).agg(m.monoid.fold(F.col("k"), m._a()).alias("a"))
    return ends.unionByName(part) if near is not q else part


def _answer(m: SummaryMap, q: DataFrame, parts: DataFrame) -> DataFrame:
    folded = parts.groupBy("qid").agg(m.monoid.fold(F.col("pos"), F.col("a")).alias("a"))
    return q.select("qid").join(folded, "qid", "left").select("qid", F.coalesce("a", m.monoid.neutral()).alias("a"))


def range_summaries_canonical(m: SummaryMap, q: DataFrame) -> DataFrame:
    """Any monoid, also where order matters: boundary folds and a cover of pyramid nodes, folded by position."""
    located = _located(m, q)
    f = m.layout.fanout
    nodes = located.filter("br - bl > 1").select("qid", F.explode(cover((F.col("bl") + 1).cast("bigint"), (F.col("br") - 1).cast("bigint"), f, _depth(m))).alias("c")).select("qid", "c.level", "c.node")
    inner = nodes.join(m.pyramid(), ["level", "node"]).select("qid", (F.col("node") * F.pow(F.lit(f), F.col("level"))).cast("bigint").alias("pos"), "a")
    return _answer(m, q, inner.unionByName(_boundaries(m, located)))


def range_summaries_prefix(m: SummaryMap, q: DataFrame) -> DataFrame:
    """Monoids with an inverse: the prefix at hi, less the prefix strictly below lo."""
    ends = q.select("qid", F.explode(F.array(F.struct(F.col("lo").alias("k"), F.lit(0).alias("tag")), F.struct(F.col("hi").alias("k"), F.lit(2).alias("tag")))).alias("e")).select("qid", "e.k", "e.tag")
    got = asof(m, ends).groupBy("qid").agg(F.max(F.when(F.col("tag") == 0, F.col("a"))).alias("below"), F.max(F.when(F.col("tag") == 2, F.col("a"))).alias("upto"))
    out = q.select("qid", "lo", "hi").join(got, "qid")
    return out.select("qid", F.when(F.col("lo") > F.col("hi"), m.monoid.neutral()).otherwise(m.monoid.inverse(F.col("below"), F.col("upto"))).alias("a"))


def window_table(m: SummaryMap) -> DataFrame:
    """(j, block, a): the summary of 2^j blocks from that one on. n log n rows in the number of blocks."""
    spark = m.rows.sparkSession
    every = spark.range(len(m.splitters) + 1).select(F.col("id").cast("int").alias("block"))
    level = every.join(m.block_table().select("block", "a"), "block", "left").select(F.lit(0).alias("j"), "block", F.coalesce("a", m.monoid.neutral()).alias("a"))
    if m.monoid.agg is not None:  # frames over the bounded block table: one pass, whatever the number of levels
        total = len(m.splitters) + 1
        ahead = lambda j: W.partitionBy(F.lit(0)).orderBy("block").rowsBetween(0, (1 << j) - 1)
        sums = [F.struct(F.lit(j).alias("j"), m.monoid.agg(F.col("a")).over(ahead(j)).alias("a")) for j in range(total.bit_length())]
        rows = level.select("block", F.array(*sums).alias("w")).select("block", F.explode("w").alias("w")).select("w.j", "block", "w.a")
        return rows.filter(F.col("block") + F.expr("shiftleft(1, j)") <= total)
    out, j = level, 0
    while 2 << j <= len(m.splitters) + 1:
        right = level.select((F.col("block") - (1 << j)).alias("block"), F.col("a").alias("b"))
        level = level.join(right, "block").select(F.lit(j + 1).alias("j"), "block", m.monoid.combine2(F.col("a"), F.col("b")).alias("a"))
        out, j = out.unionByName(level), j + 1
    return out


def range_summaries_overlap(m: SummaryMap, q: DataFrame) -> DataFrame:
    """Idempotent, commutative monoids: two windows of a power of two blocks cover the inside."""
    located = _located(m, q)
    inside = located.filter("br - bl > 1").withColumn("j", F.length(F.bin(F.greatest(F.col("br") - F.col("bl") - 1, F.lit(1)).cast("bigint"))) - 1)
    two = inside.select("qid", "j", F.explode(F.expr("array(bl + 1, br - shiftleft(1, j))")).alias("block"))
    inner = two.join(window_table(m), ["j", "block"]).select("qid", F.col("block").cast("bigint").alias("pos"), "a")
    return _answer(m, q, inner.unionByName(_boundaries(m, located)))


def range_summaries_few(m: SummaryMap, q: DataFrame) -> DataFrame:
    """A handful of ranges (qid, lo, hi) of a stored map: whole blocks from the block table, and only the blocks read that a bound cuts."""
    asked = [r for r in q.select("qid", "lo", "hi").collect() if r.lo <= r.hi]
    cut = sorted({b for r in asked for b in m.stored.between(r.lo, r.hi, "[]")[1]})
    small = F.broadcast(q.select("qid", "lo", "hi").filter("lo <= hi"))
    whole = m.stored.table.filter("n > 0").withColumnsRenamed({"lo": "first", "hi": "last"}).join(small, F.expr("lo <= first and last <= hi"))
    parts = whole.select("qid", F.col("block").cast("bigint").alias("pos"), "a")
    if cut:
        ends = m.stored.table.select("block", F.col("lo").alias("first"), F.col("hi").alias("last"))
        rows = m.stored.open(cut).join(F.broadcast(ends), "block").join(small, F.expr("k between lo and hi and not (lo <= first and last <= hi)"))
        parts = parts.unionByName(rows.groupBy("qid", F.col("block").cast("bigint").alias("pos")).agg(m.monoid.fold(F.col("k"), m._a()).alias("a")))
    return _answer(m, q, parts)


def range_summaries(m: SummaryMap, q: DataFrame, strategy: str = "auto") -> DataFrame:
    """q: qid, lo, hi (closed). (qid, a), the identity for empty or reversed ranges. `explain_choice` says what "auto" takes.
    Equal ranges are answered once."""
    if strategy == "auto":
        strategy, _ = explain_choice(m, q)
    ways = {"few": range_summaries_few, "prefix": range_summaries_prefix, "overlap": range_summaries_overlap, "canonical": range_summaries_canonical}
    if strategy == "few":
        return range_summaries_few(m, q)
    return once(q, ["lo", "hi"], lambda each: ways[strategy](m, each), ["a"])


def once(q: DataFrame, by: list[str], answer, out: list[str]) -> DataFrame:
    """Each distinct query (qid, *by) is answered once, as the least qid that asks it; `answer` gives (qid, *out)."""
    heads = q.groupBy(*by).agg(F.min("qid").alias("qid"))
    got = answer(heads).select(F.col("qid").alias("__one"), *out)
    told = heads.withColumnRenamed("qid", "__one").join(got, "__one").select(*[F.col(c).alias(f"__{c}") for c in by], *out)
    return q.join(told, [F.col(c).eqNullSafe(F.col(f"__{c}")) for c in by]).select("qid", *out)


def explain_choice(m: SummaryMap, q: DataFrame) -> tuple[str, str]:
    """(strategy, reason), from the monoid's traits, the number of queries (counted up to the small batch's bound) and the store."""
    n = q.limit(SMALL_BATCH + 1).count()
    return choose(m.monoid, n, m.stored is not None and m.stored.summed)
