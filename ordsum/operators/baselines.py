"""What the map is compared with. Each gives the same rows as the method it stands beside."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ordsum.operators.batch import once
from ordsum.operators.maps import Layout, block_of


def scan_range(entries: DataFrame, q: DataFrame) -> DataFrame:
    """Range sums by one scan of all entries, without a map or summaries: the ends of all ranges are sorted among the entries
    and told the running sum. Null for a range without values. Blocks of keys are scanned side by side; equal ranges are
    asked once."""
    return q.select("qid").join(once(q, ["lo", "hi"], lambda each: _swept(entries.select("k", "v"), each), ["a"]), "qid", "left")


def _swept(entries: DataFrame, q: DataFrame) -> DataFrame:
    cuts = Layout(block_rows=4096).splitters(entries.select("k").filter("k is not null"))
    end = lambda k, tag, sign: F.struct(F.col(k).alias("k"), F.lit(tag).alias("tag"), F.lit(sign).alias("sign"))
    ends = q.filter("lo <= hi").select("qid", F.inline(F.array(end("lo", 0, -1), end("hi", 2, 1))))
    rows = entries.filter("k is not null").withColumn("tag", F.lit(1)).unionByName(ends, allowMissingColumns=True).withColumn("block", block_of(F.col("k"), cuts))
    told = lambda w, n, v: [F.coalesce(F.sum(n).over(w), F.lit(0)).alias("n"), F.coalesce(F.sum(v).over(w), F.lit(0)).alias("s")]
    inside = W.partitionBy("block").orderBy("k", "tag").rowsBetween(W.unboundedPreceding, 0)
    run = rows.select("block", "qid", "sign", *told(inside, F.when(F.col("v").isNotNull(), 1), F.col("v"))).filter("qid is not null")
    # one row a block, and their number is bounded; blocks without entries have rows too, so that ends there find what came before
    totals = rows.groupBy("block").agg(F.count("v").alias("bn"), F.coalesce(F.sum("v"), F.lit(0)).alias("bs"))
    before = W.partitionBy(F.lit(0)).orderBy("block").rowsBetween(W.unboundedPreceding, -1)
    carry = totals.select("block", *told(before, F.col("bn"), F.col("bs"))).withColumnsRenamed({"n": "cn", "s": "cs"})
    got = run.join(F.broadcast(carry), "block").groupBy("qid").agg(F.sum(F.expr("sign * (n + cn)")).alias("n"), F.sum(F.expr("sign * (s + cs)")).alias("a"))
    return got.filter("n > 0").select("qid", "a")


def plain_filter(entries: DataFrame, pred) -> DataFrame:
    return entries.filter(pred)


def union_copy(a: DataFrame, b: DataFrame, agg=F.sum) -> DataFrame:
    """A new map of all entries, nothing shared."""
    return a.unionByName(b).groupBy("k").agg(agg("v").alias("v"))


def union_merge(a: DataFrame, b: DataFrame, h) -> DataFrame:
    """Sorted merge of both inputs."""
    both = a.hint("merge").join(b.select("k", F.col("v").alias("w")), "k", "full_outer")
    return both.select("k", F.when(F.col("v").isNull(), F.col("w")).when(F.col("w").isNull(), F.col("v")).otherwise(h(F.col("v"), F.col("w"))).alias("v"))


def bulk_merge(m: DataFrame, batch: DataFrame) -> DataFrame:
    """Insert by merging the whole map, whatever the batch's size."""
    return union_merge(m, batch, lambda old, new: new)


def insert_loop(store, rows: list[tuple]) -> int:
    """One version per row. For comparison on a few rows."""
    spark = store.spark
    schema = store.snapshot().rows.select("k", "v").schema
    for r in rows:
        v = store.insert_many(spark.createDataFrame([r], schema))
    return v


def hash_store(df: DataFrame, buckets: int = 64) -> DataFrame:
    """An unordered map: one row per key, dealt by hash."""
    return df.groupBy("k").agg(F.first("v").alias("v")).withColumn("bucket", F.pmod(F.xxhash64("k"), F.lit(buckets)))


def hash_get_many(store: DataFrame, q: DataFrame, buckets: int = 64) -> DataFrame:
    return q.withColumn("bucket", F.pmod(F.xxhash64("k"), F.lit(buckets))).join(store, ["bucket", "k"], "left").select("k", "v")


#: Rows of a query set that a nested loop may send to every task.
MOST_ASKED = 1_000_000


def _asked(q: DataFrame) -> DataFrame:
    if q.limit(MOST_ASKED + 1).count() > MOST_ASKED:
        raise ValueError(f"a nested loop is for {MOST_ASKED} queries at most")
    return F.broadcast(q)


def rect_scan(points: DataFrame, q: DataFrame) -> DataFrame:
    """(qid, *) of every point inside each rectangle, one by one: both are dealt by cells, of which a rectangle meets a few,
    and held against each other there. points: x, y and what goes with them."""
    sizes = q.filter("xl <= xr and yl <= yr").agg(F.avg(F.col("xr") - F.col("xl")).alias("x"), F.avg(F.col("yr") - F.col("yl")).alias("y")).first()
    # cells half as wide as the mean rectangle; wider rectangles meet more of them
    wide = {c: max(1, int((sizes[c] or 0) // 2)) for c in ("x", "y")}
    cell = lambda c: F.expr(f"{c} div {wide[c[0]]}L - if(pmod({c}, {wide[c[0]]}L) <> 0 and {c} < 0, 1, 0)")
    cells = lambda c: F.explode(F.sequence(cell(f"{c}l"), cell(f"{c}r")))
    spread = q.filter("xl <= xr and yl <= yr").select("qid", "xl", "xr", "yl", "yr", cells("x").alias("cx")).withColumn("cy", cells("y"))
    dealt = points.withColumns({"cx": cell("x"), "cy": cell("y")})
    met = spread.hint("merge").join(dealt, ["cx", "cy"]).filter("x between xl and xr and y between yl and yr")
    return met.select("qid", *[c for c in points.columns if c not in ("x", "y")])


def rect_sums_scan(points: DataFrame, q: DataFrame) -> DataFrame:
    """(qid, a): the weights' sum inside each rectangle that holds a point, by listing the points. Points of one place are listed
    together, equal rectangles once."""
    places = points.groupBy("x", "y").agg(F.sum("w").alias("w"))
    return once(q, ["xl", "xr", "yl", "yr"], lambda each: rect_scan(places, each).groupBy("qid").agg(F.sum("w").alias("a")), ["a"])


def interval_nlj(intervals: DataFrame, points: DataFrame) -> DataFrame:
    """Columns of the intervals besides their ends come with each stabbing."""
    met = _asked(points).join(intervals, (F.col("lo") < F.col("p")) & (F.col("p") < F.col("hi")))
    return met.select("pid", "p", *[c for c in intervals.columns if c not in ("lo", "hi")])


def interval_counts_nlj(intervals: DataFrame, points: DataFrame) -> DataFrame:
    """(pid, n): the stabbings of each point, none left out. Equal intervals are held against the points once."""
    alike = intervals.filter("lo < hi").groupBy("lo", "hi").agg(F.count("*").alias("m"))
    return interval_nlj(alike, points).groupBy("pid").agg(F.sum("m").alias("n"))


def topk_fullsort(matches: DataFrame, k: int) -> DataFrame:
    """Ranks every match of every query, then cuts. matches: qid, doc_id, w."""
    ranked = matches.withColumn("rk", F.row_number().over(W.partitionBy("qid").orderBy(F.desc("w"), "doc_id")))
    return ranked.filter(F.col("rk") <= k).select("qid", "rk", "doc_id", "w")
