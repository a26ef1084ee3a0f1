"""Inputs derived from the given tables. Times are microseconds of the zone-free timestamp, money integer cents."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

DAY = 86_400_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def micros(c: str) -> Column:
    return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', {c})")


def cents(c: str) -> Column:
    return F.round(F.col(c) * 100).cast("bigint")


def ev_map(spark, d) -> DataFrame:
    return table(spark, d, "events").select(micros("ts").alias("k"), cents("value").alias("v"), "event_id", "user_id")


def li_seq(spark, d) -> DataFrame:
    return table(spark, d, "lineitem").select(F.struct("l_orderkey", "l_linenumber").alias("k"), cents("l_extendedprice").alias("v"), "l_shipdate", "l_extendedprice", "l_partkey")


def li_ship(spark, d) -> DataFrame:
    return table(spark, d, "lineitem").select(micros("l_shipdate").alias("k"), cents("l_extendedprice").alias("v"))


def orders(spark, d) -> DataFrame:
    return table(spark, d, "orders").select(F.col("o_orderkey").alias("k"), cents("o_totalprice").alias("v"))


def ord_bars(spark, d) -> DataFrame:
    last = table(spark, d, "lineitem").groupBy("l_orderkey").agg(F.max("l_shipdate").alias("s"))
    both = table(spark, d, "orders").join(last, F.col("o_orderkey") == F.col("l_orderkey"))
    return both.select(F.col("o_orderkey").alias("id"), micros("least(o_orderdate, s)").alias("lo"), micros("greatest(o_orderdate, s)").alias("hi"), cents("o_totalprice").alias("y"))


def ord_iv(spark, d) -> DataFrame:
    return ord_bars(spark, d).select("id", "lo", "hi")


def sess_iv(spark, d) -> DataFrame:
    from pyspark.sql import Window as W

    w = W.partitionBy("user_id").orderBy("t")
    e = table(spark, d, "events").select("user_id", micros("ts").alias("t"))
    new = F.when(F.col("t") - F.lag("t").over(w) <= 6 * 3_600_000_000, 0).otherwise(1)
    s = e.withColumn("new", new).withColumn("sid", F.sum("new").over(w))
    return s.groupBy("user_id", "sid").agg(F.min("t").alias("lo"), F.max("t").alias("hi")).select((F.col("user_id") * 1_000_000 + F.col("sid")).alias("id"), "lo", "hi")


def iv_points(spark, d) -> DataFrame:
    return table(spark, d, "orders").select(micros("o_orderdate").alias("p")).distinct().select(F.col("p").alias("pid"), "p")


def li_pts(spark, d) -> DataFrame:
    t = table(spark, d, "lineitem")
    return t.select(F.struct("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate").alias("id"), F.floor(micros("l_shipdate") / DAY).alias("x"), cents("l_extendedprice").alias("y"), F.col("l_quantity").cast("bigint").alias("w"))


def q_rect(spark, d) -> DataFrame:
    t = table(spark, d, "orders")
    x, c = F.floor(micros("o_orderdate") / DAY), cents("o_totalprice")
    return t.select(F.col("o_orderkey").alias("qid"), x.alias("xl"), (x + 180).alias("xr"), F.floor(c * 18 / 100).alias("yl"), F.floor(c * 22 / 100).alias("yr"))


def q_day(spark, d) -> DataFrame:
    return ev_map(spark, d).select(F.col("event_id").alias("qid"), F.col("k").alias("lo"), (F.col("k") + DAY).alias("hi"))


def q_90d(spark, d) -> DataFrame:
    t = table(spark, d, "orders")
    return t.select(F.col("o_orderkey").alias("qid"), micros("o_orderdate").alias("lo"), (micros("o_orderdate") + 90 * DAY).alias("hi"))


def searched(q: DataFrame) -> DataFrame:
    """The query set of the methods that hold every query against every row: ids divisible by fifty."""
    return q.filter("qid % 50 = 0")


def q_and(spark, d) -> DataFrame:
    """One query per document: its least and greatest term of those in fifty documents or more."""
    from ordsum.operators.ranked_index import tokenize

    t = tokenize(table(spark, d, "documents"), "doc_id", "text").distinct()
    frequent = t.groupBy("term").count().filter("count >= 50").select("term")
    ends = t.join(frequent, "term").groupBy("doc_id").agg(F.min("term").alias("t1"), F.max("term").alias("t2")).filter("t1 <> t2")
    return ends.select(F.col("doc_id").alias("qid"), F.array("t1", "t2").alias("terms"))
