"""Intervals by left end with the greatest right end as summary. Both ends are strict: lo < p < hi."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ordsum.functions.monoids import count, max_, sum_
from ordsum.operators.batch import asof, cover
from ordsum.operators.maps import MOST_BLOCKS, Layout, SummaryMap, block_of, union


def _filed(intervals: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Intervals under the power of two above their length (c) and their cell of that width; and the c there are, 64 at most."""
    c = F.length(F.bin((F.col("hi") - F.col("lo")).cast("bigint")))
    filed = intervals.withColumn("c", c).withColumn("cell", F.expr("shiftright(lo, c)"))
    return filed, F.broadcast(filed.select("c").distinct())


def _asked(points: DataFrame, classes: DataFrame) -> DataFrame:
    """Each point (p) under the cells in which an interval that holds it may be filed."""
    return points.crossJoin(classes).select("*", F.explode(F.array(F.expr("shiftright(p, c)"), F.expr("shiftright(p, c) - 1"))).alias("cell"))


def _strips(filed: DataFrame, points: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Where points ask for a height (ylo, yhi; closed) of intervals at y: strips as high as the highest asks, of which a
    point asks two at most."""
    high = points.agg(F.max(F.col("yhi") - F.col("ylo")).alias("w")).first().w
    width = max(1, int(high or 0))
    strip = lambda y: F.expr(f"{y} - pmod({y}, {width}L)")
    return filed.withColumn("strip", strip("y")), points.filter("ylo <= yhi").withColumn("strip", F.explode(F.array_distinct(F.array(strip("ylo"), strip("yhi")))))


#: From this chance on that an interval of one table meets one of another, cells of time would spare too few pairs to be worth their rows.
LONG = 1 / 8


def _share(a: DataFrame, b: DataFrame) -> float:
    """How likely an interval of a meets one of b, if both lie anywhere in the extent of all: from their mean lengths."""
    seen = [x.filter("lo <= hi").agg(F.avg(F.col("hi") - F.col("lo")).alias("mean"), F.min("lo").alias("lo"), F.max("hi").alias("hi")).first() for x in (a, b)]
    if any(r.mean is None for r in seen):
        return 0.0
    extent = max(r.hi for r in seen) - min(r.lo for r in seen)
    return min(1.0, sum(r.mean for r in seen) / extent) if extent else 1.0


def stab_pairs(intervals: DataFrame, points: DataFrame) -> DataFrame:
    """(pid, p, id) of all stabbings. Intervals are filed once, under the power of two above their length.

    If points have ylo and yhi, only intervals whose y lies between these are met. Where intervals are long beside the
    whole extent, heights alone part them."""
    by, inside = ["c", "cell"], "lo < p and p < hi"
    if "ylo" in points.columns:
        inside = f"{inside} and y between ylo and yhi"
        if _share(intervals, points.select(F.col("p").alias("lo"), F.col("p").alias("hi"))) >= LONG:
            filed, points = _strips(intervals.filter("lo < hi"), points)
            return filed.join(points, "strip").filter(inside).select("pid", "p", "id")
        intervals, points = _strips(intervals, points)
        by = [*by, "strip"]
    filed, classes = _filed(intervals.filter("lo < hi"))
    return _asked(points, classes).join(filed, by).filter(inside).select("pid", "p", "id")


def overlap_pairs(a: DataFrame, b: DataFrame) -> DataFrame:
    """(aid, bid) of closed intervals that meet: a begins inside b, or b begins inside a.

    If a has ylo and yhi, only those of b whose y lies between these are met. Where intervals are long beside the whole
    extent, most pairs meet: then heights alone part them, and each interval travels once."""
    high = "ylo" in a.columns
    if high and _share(a, b) >= LONG:
        ends, asked = _strips(b.filter("lo <= hi"), a.filter("lo <= hi").withColumnsRenamed({"id": "aid", "lo": "alo", "hi": "ahi"}))
        return ends.join(asked, "strip").filter("alo <= hi and lo <= ahi and y between ylo and yhi").select("aid", F.col("id").alias("bid"))

    def begins_inside(x: DataFrame, y: DataFrame) -> DataFrame:
        points, ends = x.filter("lo <= hi").withColumnsRenamed({"id": "xid", "lo": "p"}).drop("hi"), y.filter("lo <= hi")
        by, near = ["c", "cell"], F.lit(True)
        if high and x is a:
            ends, points = _strips(ends, points)
        elif high:
            points, ends = _strips(points, ends)
        if high:
            by, near = [*by, "strip"], F.expr("y between ylo and yhi")
        filed, classes = _filed(ends)
        both = _asked(points, classes).join(filed, by).filter("lo <= p and p <= hi").filter(near)
        return both.select("xid", F.col("id").alias("yid"), (F.col("p") > F.col("lo")).alias("later"))

    one = begins_inside(a, b).select(F.col("xid").alias("aid"), F.col("yid").alias("bid"))
    two = begins_inside(b, a).filter("later").select(F.col("yid").alias("aid"), F.col("xid").alias("bid"))
    return one.unionByName(two)


def overlap_totals(a: DataFrame, b: DataFrame) -> DataFrame:
    """(aid, n, total): how many closed intervals of b meet each of a, and the sum of their ids; without those that meet none.

    No pair is made: they are those that begin at or before its end, less those that end before its beginning."""
    end = lambda c, begins: F.struct(F.col(c).alias("k"), F.lit(begins).alias("begins"))
    ids = lambda begins: F.when(F.col("begins") == begins, F.col("id"))
    sums = {f"{f.__name__}_{name}": F.coalesce(f(ids(begins)), F.lit(0)).cast("bigint") for f in (F.count, F.sum) for name, begins in (("begun", True), ("ended", False))}
    both = b.filter("lo <= hi").select("id", F.inline(F.array(end("lo", True), end("hi", False)))).groupBy("k").agg(F.struct(*[x.alias(name) for name, x in sums.items()]).alias("v"))
    m, asked = SummaryMap.build(both, "k", "v", h="all", layout=Layout(block_rows=512)), a.filter("lo <= hi")
    out = asked.select(F.col("id").alias("qid"))
    for name in sums:
        c, tag = ("hi", 2) if name.endswith("begun") else ("lo", 0)
        each = replace(m, monoid=sum_(), base=lambda k, v, name=name: v[name])
        out = out.join(asof(each, asked.select(F.col("id").alias("qid"), F.col(c).alias("k"), F.lit(tag).alias("tag"))).select("qid", F.col("a").alias(name)), "qid")
    return out.select(F.col("qid").alias("aid"), F.expr("count_begun - count_ended").alias("n"), F.expr("sum_begun - sum_ended").alias("total")).filter("n > 0")


@dataclass(frozen=True)
class IntervalMap:
    """source: id, lo, hi (integers). `by_lo` holds one entry per left end."""

    source: DataFrame
    by_lo: SummaryMap

    @staticmethod
    def build(df: DataFrame, layout: Layout = Layout(block_rows=512)) -> "IntervalMap":
        src = df.select("id", F.col("lo").cast("bigint"), F.col("hi").cast("bigint"))
        m = SummaryMap.build(src.groupBy("lo").agg(F.max("hi").alias("hi")), "lo", "hi", max_(), layout=layout)
        return IntervalMap(src, m)

    def stab_many(self, points: DataFrame) -> DataFrame:
        """points: pid, p. (pid, p, covered): the greatest right end of what starts before p lies after p."""
        got = asof(self.by_lo, points.select(F.col("pid").alias("qid"), F.col("p").alias("k"), F.lit(0).alias("tag")))
        return got.select(F.col("qid").alias("pid"), F.col("k").alias("p"), F.coalesce(F.col("a") > F.col("k"), F.lit(False)).alias("covered"))

    def stab(self, p: int) -> DataFrame:
        return self.by_lo.summary_left(p, inclusive=False).select(F.coalesce(F.col("a") > p, F.lit(False)).alias("covered"))

    def report(self, p: int) -> DataFrame:
        starts = self.by_lo.up_to(p, inclusive=False).summary_filter(lambda a: a > p).rows.select(F.col("k").alias("lo"))
        return self.source.join(starts, "lo", "left_semi").filter(F.col("hi") > p).select("id", "lo", "hi")

    def report_by_extraction(self, p: int) -> list[int]:
        """Left ends, each the one of the greatest right end among those left. For differential tests on small maps."""
        left, out = self.by_lo.up_to(p, inclusive=False), []
        while True:
            top = left.rows.orderBy(F.desc("v"), "k").limit(1).collect()
            if not top or top[0].v <= p:
                return sorted(out)
            out.append(top[0].k)
            left = left.delete(top[0].k)

    def report_many(self, points: DataFrame) -> DataFrame:
        return stab_pairs(self.source, points)

    def count_many(self, points: DataFrame) -> DataFrame:
        """(pid, n): left ends before p less right ends at or before it."""
        ok = self.source.filter("lo < hi")
        by = lambda c: SummaryMap.build(ok.groupBy(c).agg(F.count("*").alias("m")), c, "m", _times(), layout=self.by_lo.layout)
        q = lambda tag: points.select(F.col("pid").alias("qid"), F.col("p").alias("k"), F.lit(tag).alias("tag"))
        begun, ended = asof(by("lo"), q(0)).select("qid", F.col("a").alias("x")), asof(by("hi"), q(2)).select("qid", F.col("a").alias("y"))
        return begun.join(ended, "qid").select(F.col("qid").alias("pid"), (F.col("x") - F.col("y")).alias("n"))

    def insert(self, id_: int, lo: int, hi: int) -> "IntervalMap":
        one = self.source.sparkSession.range(1).select(F.lit(id_).cast(self.source.schema["id"].dataType).alias("id"), F.lit(lo).cast("bigint").alias("lo"), F.lit(hi).cast("bigint").alias("hi"))
        return IntervalMap(self.source.unionByName(one), self.by_lo.insert(lo, hi, lambda old, new: F.greatest(old, new)))

    def delete(self, ids: DataFrame) -> "IntervalMap":
        """Without the intervals of these ids. Only left ends that lose one are summed up anew."""
        gone = self.source.join(ids.select("id"), "id", "left_semi").select("lo").distinct()
        rest = self.source.join(ids.select("id"), "id", "left_anti")
        anew = rest.join(gone, "lo", "left_semi").groupBy(F.col("lo").alias("k")).agg(F.max("hi").alias("v"))
        return IntervalMap(rest, self.by_lo.delete_many(gone.select(F.col("lo").alias("k"))).insert_many(anew))

    def union(self, other: "IntervalMap") -> "IntervalMap":
        """Intervals of both; of equal left ends the greater right end is kept in the map."""
        return IntervalMap(self.source.unionByName(other.source), union(self.by_lo, other.by_lo, lambda a, b: F.greatest(a, b)))

    def drop_shorter(self, least: int) -> DataFrame:
        return self.source.filter(F.col("hi") - F.col("lo") >= least)


def _times():
    from ordsum.functions.monoids import sum_

    return sum_()


def segments_crossing(h: DataFrame, v: DataFrame) -> DataFrame:
    """h: id, lo, hi, y; v: id, x, ylo, yhi. Crossings of level and upright segments (open along h, closed along v)."""
    pairs = stab_pairs(h, v.select(F.col("id").alias("pid"), F.col("x").alias("p"), "ylo", "yhi"))
    return pairs.select(F.col("id").alias("hid"), F.col("pid").alias("vid"))


def locate(h: DataFrame, p: DataFrame) -> DataFrame:
    """p: pid, x, y. The level segment next below each point, ties to the larger id. Equal points are located once.

    No stabbing is listed: the places x that are asked for are numbered, a segment is filed under the few nodes of a binary
    tree over them that it spans, and a point looks in the nodes above it for the last segment at or below its height."""
    spots = p.groupBy("x", "y").agg(F.min("pid").alias("one"))
    numbered, spans, n = _numbered(spots, h.filter("lo < hi").withColumnRenamed("y", "hy"))
    if not n:
        return p.join(h.select(F.col("id").alias("hid")).limit(0), F.lit(True)).select("pid", "hid")
    depth = (n - 1).bit_length()
    # segments alike are one; all nodes in a row, those of a level after the ones below it
    spans = spans.filter("first <= last").groupBy("first", "last", "hy").agg(F.max("id").alias("id"))
    nodes = F.explode(cover(F.col("first"), F.col("last"), 2, depth))
    number = lambda level, node: F.expr(f"shiftleft(cast({level} as bigint), 48) + {node}")
    filed = spans.select("hy", "id", nodes.alias("c")).select(number("c.level", "c.node").alias("node"), F.col("hy").alias("y"), "id")
    above = F.explode(F.array(*[number(d, f"shiftright(i, {d})") for d in range(depth + 1)]))
    asked = numbered.select("one", "y", above.alias("node"))
    # a node's segments lie in strips of heights, of which each tells those above it its highest
    cuts = Layout(block_rows=1 << 16).splitters(h.select(F.col("y").alias("k")).filter("k is not null"))
    both = filed.unionByName(asked, allowMissingColumns=True).withColumn("strip", block_of(F.col("y"), cuts).cast("int"))
    here = F.when(F.col("id").isNotNull(), F.struct("y", "id"))
    inside = W.partitionBy("node", "strip").orderBy("y", F.col("one").isNotNull(), "id").rowsBetween(W.unboundedPreceding, 0)
    found = both.select("node", "strip", "one", F.last(here, True).over(inside).alias("best")).filter("one is not null")
    below = W.partitionBy("node").orderBy("strip").rowsBetween(W.unboundedPreceding, -1)
    carry = both.groupBy("node", "strip").agg(F.max(here).alias("top")).select("node", "strip", F.last("top", True).over(below).alias("lower"))
    found = found.join(carry, ["node", "strip"]).groupBy("one").agg(F.max(F.coalesce("best", "lower")).alias("best")).filter("best is not null")
    return p.join(spots, ["x", "y"]).join(found, "one").select("pid", F.col("best.id").alias("hid"))


def _numbered(spots: DataFrame, h: DataFrame) -> tuple[DataFrame, DataFrame, int]:
    """The places x of points in order: points with the number (i) of theirs, segments (hy, id) with the first and the last
    place inside, and how many places there are."""
    places = spots.filter("x is not null").select("x").distinct()
    some = [r.x for r in places.limit(MOST_BLOCKS).collect()]
    if len(some) < MOST_BLOCKS:
        some.sort()
        at = lambda c: block_of(F.expr(c), some).cast("bigint")
        # block_of counts the places at or below
        return spots.filter("x is not null").withColumn("i", at("x") - 1), h.select("hy", "id", at("lo").alias("first"), (at("hi - 1") - 1).alias("last")), len(some)
    m = SummaryMap.build(places, "x", F.lit(0), layout=Layout(block_rows=512))
    ends = h.select(F.inline(F.array(*[F.struct(F.col(c).alias("k"), F.lit(tag).alias("tag")) for c, tag in (("lo", 2), ("hi", 0))]))).distinct()
    ranked = asof(m, ends.withColumn("qid", F.lit(0))).select("k", "tag", "n")
    side = lambda c, tag, name: ranked.filter(F.col("tag") == tag).select(F.col("k").alias(c), F.col("n").alias(name))
    spans = h.join(side("lo", 2, "first"), "lo").join(side("hi", 0, "end"), "hi").select("hy", "id", "first", (F.col("end") - 1).alias("last"))
    i = m.ranked().select(F.col("k").alias("x"), F.col("r").cast("bigint").alias("i"))
    return spots.join(i, "x"), spans, places.count()
