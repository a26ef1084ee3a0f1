"""Weighted points in the plane: an outer order by x whose nodes hold their points by y.

The nested map is one flat table (level, node, child, yb, y, w, n), kept on disk where the index
is stored: level 0 nodes are blocks of points by x, a node of a higher level has `fanout`
nodes below it. n points of one block, y and weight are one row. Bounds are closed.

Sums (any monoid with an inverse) go by dominance: the four corners of each rectangle ask
for all that lies at or below them, a corner's blocks before its own are some children of
one node on each level, and in each node one sorted pass by y, cut into y-buckets with
carried sums, answers every corner at once. Other monoids take the few whole nodes under an
x-range and ask in each for a range of y, as ranges of one map over (level, node, y). Up to `MOST_BLOCKS`
values of x are blocks of their own, so a bound cuts none; beyond that, blocks hold neighbouring values and
the rows of cut ones are looked at. Equal rectangles are answered once.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ordsum.functions.monoids import Monoid, sum_
from ordsum.operators.batch import _depth, cover, once, range_summaries
from ordsum.operators.maps import MOST_BLOCKS, Layout, SummaryMap, block_of
from ordsum.sources import scratch

SIDES = ["xl", "xr", "yl", "yr"]


@dataclass(frozen=True)
class RectIndex:
    points: DataFrame  # id, x, y, w, block
    outer: SummaryMap  # x -> points of that x
    y_splitters: list
    depth: int
    nested: DataFrame | None = None  # the levels, where they are stored
    exact: bool = False  # whether block i holds the points of the i-th value of x, block 0 none

    @staticmethod
    def build(df: DataFrame, layout: Layout = Layout(block_rows=256, fanout=8), y_rows: int = 2048) -> "RectIndex":
        src = df.select("id", F.col("x").cast("bigint"), F.col("y").cast("bigint"), F.col("w").cast("bigint"))
        xs = src.groupBy("x").agg(F.count("*").alias("n"))
        outer = SummaryMap.build(xs, "x", "n", sum_(), layout=Layout(layout.policy, max(1, layout.block_rows // 16), layout.fanout))
        ys = Layout(block_rows=y_rows).splitters(src.select(F.col("y").alias("k")))
        found = xs.select("x").limit(MOST_BLOCKS).collect()
        exact = len(found) < MOST_BLOCKS
        if exact:
            outer = replace(outer, splitters=sorted(r.x for r in found)).with_rows(outer.rows)
        # a bound may lie behind the last block
        depth = _depth(replace(outer, splitters=[*outer.splitters, 0]))
        return RectIndex(src.withColumn("block", block_of(F.col("x"), outer.splitters)), outer, ys, depth, exact=exact)

    def store(self, path: str) -> "RectIndex":
        """The same index with its inner maps on disk, in the order in which queries meet them. Its points, which only
        listings and cut blocks ask for, are read from where they lie."""
        spark = self.points.sparkSession
        self.levels().repartition("level", "node", "yb").sortWithinPartitions("level", "node", "yb", "y").write.parquet(f"{path}/levels")
        return replace(self, nested=spark.read.parquet(f"{path}/levels"))

    def _at(self, block, level: int):
        return F.floor(block / F.lit(self.outer.layout.fanout**level)).cast("bigint")

    def levels(self) -> DataFrame:
        """(level, node, child, yb, y, w, n): every point once per level, n alike in one row; child is its node one level
        below, within this one."""
        if self.nested is not None:
            return self.nested
        f, b = self.outer.layout.fanout, F.col("block")
        nodes = [F.struct(F.lit(d).alias("level"), self._at(b, d).alias("node"), (self._at(b, max(0, d - 1)) % f).cast("int").alias("child")) for d in range(self.depth + 1)]
        alike = self.points.groupBy("block", "y", "w").agg(F.count("*").alias("n"))
        out = alike.select("y", "w", "n", block_of(F.col("y"), self.y_splitters).cast("int").alias("yb"), F.explode(F.array(*nodes)).alias("c"))
        return out.select("c.level", "c.node", "c.child", "yb", "y", "w", "n")

    def sums_many(self, q: DataFrame) -> DataFrame:
        """q: qid, xl, xr, yl, yr. (qid, a): the weights' sum inside each rectangle, by dominance of its corners."""
        return once(q, SIDES, self._sums, ["a"])

    def _sums(self, q: DataFrame) -> DataFrame:
        f = self.outer.layout.fanout
        corner = lambda x, y, s: F.struct(F.expr(x).cast("bigint").alias("x"), F.expr(y).cast("bigint").alias("y"), F.lit(s).alias("s"))
        four = F.array(corner("xr", "yr", 1), corner("xl - 1", "yr", -1), corner("xr", "yl - 1", -1), corner("xl - 1", "yl - 1", 1))
        asked = q.filter("xl <= xr and yl <= yr").select("qid", F.explode(four).alias("c")).select("qid", "c.*")
        asked = asked.withColumns({"block": block_of(F.col("x"), self.outer.splitters), "yb": block_of(F.col("y"), self.y_splitters).cast("int")})
        # the blocks before a corner's own: on each level the children before its own of the node that holds it
        b = F.col("block") + int(self.exact)  # an exact corner's own block is dominated whole
        steps = [F.struct(F.lit(d).alias("level"), self._at(b, d).alias("node"), (self._at(b, d - 1) % f).cast("int").alias("child")) for d in range(1, self.depth + 1)]
        none, total = F.lit(None), F.lit(None).cast("bigint")
        if steps:
            steps = asked.select("qid", "s", "yb", "y", F.explode(F.array(*steps)).alias("c")).filter("c.child > 0")
            steps = steps.select("c.level", "c.node", "c.child", "yb", "y", "qid", "s", total.alias("w"))
            rows = self.levels().filter("level > 0").select("level", "node", "child", "yb", "y", none.cast("bigint").alias("qid"), none.cast("int").alias("s"), (F.col("w") * F.col("n")).alias("w"))
            before = [F.when(F.col("child") < j, F.col("w")) for j in range(1, f)]
            names = [f"p{j}" for j in range(1, f)]
            # whole y-buckets below: sums of each, carried
            cells = rows.groupBy("level", "node", "yb").agg(*[F.sum(x).alias(n) for x, n in zip(before, names)])
            # a corner may stand in a bucket without points: it takes the carry of the last bucket at or before it
            cell = cells.unionByName(steps.select("level", "node", "yb").distinct(), allowMissingColumns=True).groupBy("level", "node", "yb").agg(*[F.sum(n).alias(n) for n in names])
            upto = W.partitionBy("level", "node").orderBy("yb").rowsBetween(W.unboundedPreceding, -1)
            carry = cell.select("level", "node", "yb", *[F.coalesce(F.sum(n).over(upto), F.lit(0)).alias(f"c{n}") for n in names])
            inside = W.partitionBy("level", "node", "yb").orderBy("y", F.col("qid").isNotNull()).rowsBetween(W.unboundedPreceding, 0)
            run = rows.unionByName(steps).select("level", "node", "yb", "child", "qid", "s", *[F.coalesce(F.sum(F.when(F.col("qid").isNull(), x)).over(inside), F.lit(0)).alias(n) for x, n in zip(before, names)])
            got = run.filter("qid is not null").join(carry, ["level", "node", "yb"])
            pick = F.element_at(F.array(*[F.col(n) + F.col(f"c{n}") for n in names]), F.col("child"))
            whole = got.select("qid", (pick * F.col("s")).alias("a"))
        else:
            whole = asked.select("qid", F.lit(0).cast("bigint").alias("a")).limit(0)
        parts = whole
        if not self.exact:
            own = asked.join(self.points.select("block", F.col("x").alias("px"), F.col("y").alias("py"), "w"), "block").filter("px <= x and py <= y")
            parts = whole.unionByName(own.groupBy("qid").agg(F.sum(F.col("w") * F.col("s")).alias("a")))
        out = parts.groupBy("qid").agg(F.sum("a").alias("a"))
        return q.select("qid").join(out, "qid", "left").select("qid", F.coalesce("a", F.lit(0)).alias("a"))

    def agg_many(self, q: DataFrame, monoid: Monoid | None = None) -> DataFrame:
        """q: qid, xl, xr, yl, yr. (qid, a): the weights' summary inside each rectangle. monoid: commutative."""
        m = monoid or sum_()
        return self.sums_many(q) if m.name == "sum" else self.cover_many(q, m)

    def cover_many(self, q: DataFrame, m: Monoid) -> DataFrame:
        """The same for any commutative monoid, by whole nodes in x, a range of y in each, and the rows of cut blocks."""
        return once(q, SIDES, lambda each: self._covered(each, m), ["a"])

    def _covered(self, q: DataFrame, m: Monoid) -> DataFrame:
        at = q.filter("xl <= xr and yl <= yr")
        place = lambda c: block_of(F.expr(c), self.outer.splitters).cast("bigint")
        first, last = (place("xl - 1") + 1, place("xr")) if self.exact else (place("xl") + 1, place("xr") - 1)
        nodes = at.select("qid", "yl", "yr", first.alias("bl"), last.alias("br")).filter("bl <= br")
        nodes = nodes.select("qid", "yl", "yr", F.posexplode(cover(F.col("bl"), F.col("br"), self.outer.layout.fanout, self.depth)).alias("at", "c"))
        levels = self.levels()
        ends = levels.agg(F.min("y").alias("lo"), F.max("y").alias("hi")).first()
        got = None
        if ends.lo is not None:
            # (level, node, y) as one number: the nodes of all levels in a row, each with room for every y
            room, before = ends.hi - ends.lo + 1, [0]
            for d in range(self.depth + 1):
                before.append(before[-1] + (len(self.outer.splitters) + 1) // self.outer.layout.fanout**d + 1)
            if before[-1] * room >= 1 << 63:
                raise ValueError("values of y lie too far apart")
            base = (F.element_at(F.array(*[F.lit(x).cast("bigint") for x in before]), F.col("level") + 1) + F.col("node")) * room - ends.lo
            inner = SummaryMap.build(_repeated(levels, m).select((base + F.col("y")).alias("k"), F.col("v").cast(m.dtype).alias("v")), "k", "v", m, h="all", layout=Layout(block_rows=1024))
            most = 2 * self.outer.layout.fanout * (self.depth + 1)  # nodes of one cover
            asks = nodes.select((F.col("qid") * most + F.col("at")).alias("qid"), "c.*", F.greatest("yl", F.lit(ends.lo)).alias("yl"), F.least("yr", F.lit(ends.hi)).alias("yr")).filter("yl <= yr")
            asks = _written(asks.select("qid", (base + F.col("yl")).alias("lo"), (base + F.col("yr")).alias("hi")))
            # each is read several times below: the driver would plan and compile all that leads to them as often
            inner = replace(inner, rows=_written(inner.rows))
            got = range_summaries(inner, asks, "overlap" if m.idempotent else "canonical").select(F.expr(f"(qid - pmod(qid, {most})) div {most}").alias("qid"), "a")
        if not self.exact:
            cut = at.select("qid", *SIDES, F.explode(F.array_distinct(F.array(place("xl"), place("xr")))).alias("block"))
            rows = cut.join(self.points, "block").filter("x between xl and xr and y between yl and yr").select("qid", F.col("w").cast(m.dtype).alias("a"))
            got = rows if got is None else got.unionByName(rows)
        if got is None:
            return q.select("qid", m.neutral().alias("a"))
        got = got.groupBy("qid").agg(m.total(F.col("a")).alias("a"))
        return q.select("qid").join(got, "qid", "left").select("qid", F.coalesce("a", m.neutral()).alias("a"))

    def count_many(self, q: DataFrame) -> DataFrame:
        one = lambda t: t.withColumn("w", F.lit(1).cast("bigint"))
        return replace(self, points=one(self.points), nested=None if self.nested is None else one(self.nested)).agg_many(q)

    def list_many(self, q: DataFrame) -> DataFrame:
        """(qid, id) of all points inside: candidate (x-blocks, y-bucket) cells by equi-join, then the bounds."""
        some = lambda block: F.floor(block / F.lit(16 if self.exact else 1)).cast("int")
        at = q.filter("xl <= xr and yl <= yr").withColumns({"bl": some(block_of(F.col("xl"), self.outer.splitters)), "br": some(block_of(F.col("xr"), self.outer.splitters)), "cl": block_of(F.col("yl"), self.y_splitters), "cr": block_of(F.col("yr"), self.y_splitters)})
        cells = at.select("qid", "xl", "xr", "yl", "yr", "cl", "cr", F.explode(F.sequence("bl", "br")).alias("block")).withColumn("yb", F.explode(F.sequence("cl", "cr"))).drop("cl", "cr")
        pts = self.points.withColumns({"yb": block_of(F.col("y"), self.y_splitters), "block": some(F.col("block"))})
        return cells.hint("merge").join(pts, ["block", "yb"]).filter("x between xl and xr and y between yl and yr").select("qid", "id")


def _written(df: DataFrame) -> DataFrame:
    spark = df.sparkSession
    path = scratch.place(spark, "covered")
    df.write.parquet(path)
    return spark.read.parquet(path)


def _repeated(levels: DataFrame, m: Monoid) -> DataFrame:
    """Values (v) that come to the same as every point's weight: each once where repeats don't count, else n times."""
    if m.idempotent:
        return levels.withColumn("v", F.col("w"))
    if m.name == "sum":
        return levels.withColumn("v", F.col("w") * F.col("n"))
    return levels.withColumn("v", F.explode(F.expr("array_repeat(w, cast(n as int))")))
