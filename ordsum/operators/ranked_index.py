"""Ranked boolean search: term -> (document -> weight), with block maxima for early ends."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

DOC_BLOCK = 64
#: Distinct queries that are sent to every task; beyond that their postings are joined instead.
MOST_SETS = 1_000_000
#: Postings that one task holds at a time.
PART_ROWS = 2_000_000


def tokenize(df: DataFrame, id_col: str, text: str | Column, alphabet: str = "unicode", markup: bool = False) -> DataFrame:
    """(doc_id, term), one row per token."""
    text = F.col(text) if isinstance(text, str) else text
    if markup:
        text = F.regexp_replace(text, "<[^>]*>", " ")
    split = r"[^\p{L}\p{N}]+" if alphabet == "unicode" else "[^a-z0-9]+"
    return df.select(F.col(id_col).alias("doc_id"), F.explode(F.split(F.lower(text), split)).alias("term")).filter("term <> ''")


def random_weight() -> Column:
    """A fixed pseudo-random weight in 0..999 of document and term."""
    return (F.conv(F.substring(F.md5(F.concat_ws("|", F.col("doc_id").cast("string"), "term")), 1, 8), 16, 10).cast("bigint") % 1000).alias("w")


def weigh(tokens: DataFrame, model: str = "random", quality: DataFrame | None = None) -> DataFrame:
    """(term, doc_id, tf, w). Models: random, tf, or tf times one plus a document's quality (doc_id, quality)."""
    tf = tokens.groupBy("term", "doc_id").agg(F.count("*").alias("tf"))
    if model == "random":
        return tf.select("term", "doc_id", "tf", random_weight())
    if model == "tf":
        return tf.withColumn("w", F.col("tf"))
    return tf.join(quality.select("doc_id", "quality"), "doc_id", "left").select("term", "doc_id", "tf", (F.col("tf") * (1 + F.coalesce("quality", F.lit(0)))).alias("w"))


@dataclass(frozen=True)
class RankedIndex:
    postings: DataFrame  # term, doc_id, w

    @staticmethod
    def build(triples: DataFrame, h: str = "sum") -> "RankedIndex":
        """triples: term, doc_id, w; weights of a pair that comes more than once are combined by h."""
        return RankedIndex(triples.groupBy("term", "doc_id").agg((F.sum if h == "sum" else F.max)("w").cast("bigint").alias("w")))

    def clustered(self) -> DataFrame:
        """The postings as they should lie on disk: each file sorted by term and document. They stay where their
        counting dealt them: a further exchange by ranges would write them all once more."""
        return self.postings.sortWithinPartitions("term", "doc_id")

    def terms(self) -> DataFrame:
        return self.postings.groupBy("term").agg(F.count("*").alias("df"), F.sum("w").alias("sum_w"), F.max("w").alias("max_w"))

    def block_maxima(self) -> DataFrame:
        return self.postings.groupBy("term", F.floor(F.col("doc_id") / DOC_BLOCK).alias("block")).agg(F.count("*").alias("n"), F.max("w").alias("max_w"))

    def _of(self, terms: list[str]) -> DataFrame:
        return self.postings.filter(F.col("term").isin(terms))

    def search_and(self, terms: list[str]) -> DataFrame:
        terms = sorted(set(terms))
        return self._of(terms).groupBy("doc_id").agg(F.sum("w").alias("w"), F.count("*").alias("n")).filter(F.col("n") == len(terms)).select("doc_id", "w")

    def search_or(self, terms: list[str]) -> DataFrame:
        return self._of(sorted(set(terms))).groupBy("doc_id").agg(F.sum("w").alias("w"))

    def search_and_not(self, positive: str, negative: str) -> DataFrame:
        return self._of([positive]).join(self._of([negative]).select("doc_id"), "doc_id", "left_anti").select("doc_id", "w")

    def search_batch(self, q: DataFrame, mode: str = "and", k: int = 10) -> DataFrame:
        """q: qid, terms. (qid, rk, doc_id, w), k best each. Equal queries are answered once."""
        sets = q.select("qid", F.array_sort(F.array_distinct("terms")).alias("terms"))
        if mode == "and":
            found = self.matches(sets, k)
            if found is not None:
                known, got = found
                best = got.withColumn("rk", F.row_number().over(W.partitionBy("sid").orderBy(F.desc("w"), "doc_id"))).filter(F.col("rk") <= k)
                return sets.join(known, "terms").join(best, "sid").select("qid", "rk", "doc_id", "w")
        distinct = sets.select("terms").distinct().withColumn("n", F.size("terms"))
        asked = distinct.select("terms", "n", F.explode("terms").alias("term"))
        got = asked.join(self.postings, "term").groupBy("terms", "n", "doc_id").agg(F.sum("w").alias("w"), F.count("*").alias("m"))
        if mode == "and":
            got = got.filter("m = n")
        best = got.withColumn("rk", F.row_number().over(W.partitionBy("terms").orderBy(F.desc("w"), "doc_id"))).filter(F.col("rk") <= k)
        return sets.join(best.select("terms", "rk", "doc_id", "w"), "terms").select("qid", "rk", "doc_id", "w")

    def matches(self, sets: DataFrame, k: int | None = None) -> tuple[DataFrame, DataFrame] | None:
        """sets: terms (sorted, distinct). (sid, terms) of the distinct ones, and (sid, doc_id, w) of the documents that
        have all terms of a set; with k, of each part of the documents the k best. None if there are too many sets.

        The postings of terms that are asked for travel once, by document, whatever the number of sets; in each part
        the rarest term's documents are looked up among the others'."""
        known = [r.terms for r in sets.select("terms").distinct().limit(MOST_SETS + 1).collect()]
        if len(known) > MOST_SETS:
            return None
        spark, known = self.postings.sparkSession, sorted(known)
        number = {t: i for i, t in enumerate(sorted({t for terms in known for t in terms}))}
        asked = [np.array([number[t] for t in terms], dtype=np.int32) for terms in known]

        def meet(part: pd.DataFrame) -> pd.DataFrame:
            tid, doc, w = (part[c].to_numpy() for c in ("tid", "doc_id", "w"))
            order = np.lexsort((doc, tid))
            tid, doc, w = tid[order], doc[order], w[order]
            ends = np.searchsorted(tid, np.arange(len(number) + 1))
            size = np.diff(ends)
            sids, docs, ws = [], [], []
            for sid, terms in enumerate(asked):
                if not len(terms) or not size[terms].all():
                    continue
                terms = terms[np.argsort(size[terms], kind="stable")]
                own = slice(ends[terms[0]], ends[terms[0] + 1])
                d, total = doc[own], w[own]
                for t in terms[1:]:
                    there = doc[ends[t] : ends[t + 1]]
                    at = np.minimum(np.searchsorted(there, d), len(there) - 1)
                    same = there[at] == d
                    d, total = d[same], total[same] + w[ends[t] + at[same]]
                if k is not None and len(d) > k:
                    best = np.lexsort((d, -total))[:k]
                    d, total = d[best], total[best]
                if len(d):
                    sids.append(np.full(len(d), sid, dtype=np.int32))
                    docs.append(d)
                    ws.append(total)
            if not sids:
                return pd.DataFrame({"sid": np.empty(0, np.int32), "doc_id": doc[:0], "w": w[:0]})
            return pd.DataFrame({"sid": np.concatenate(sids), "doc_id": np.concatenate(docs), "w": np.concatenate(ws)})

        parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-self.postings.count() // PART_ROWS))
        numbers = spark.createDataFrame(list(number.items()), "term string, tid int")
        rows = self.postings.join(F.broadcast(numbers), "term").select("tid", "doc_id", "w", F.pmod(F.xxhash64("doc_id"), F.lit(parts)).cast("int").alias("part"))
        got = rows.groupBy("part").applyInPandas(meet, "sid int, doc_id bigint, w bigint")
        return spark.createDataFrame(list(enumerate(known)), "sid int, terms array<string>"), got

    def top_k(self, terms: list[str], mode: str = "and", k: int = 10, first: int = 4) -> DataFrame:
        """Exact k best in two rounds: the best document blocks by their maxima set a threshold,
        then every block whose bound reaches it is looked at. Weights must not be negative."""
        terms = sorted(set(terms))
        bounds = self.block_maxima().filter(F.col("term").isin(terms)).groupBy("block").agg(F.sum("max_w").alias("most"), F.count("*").alias("m"))
        if mode == "and":
            bounds = bounds.filter(F.col("m") == len(terms))

        def best(blocks: DataFrame) -> DataFrame:
            rows = self._of(terms).withColumn("block", F.floor(F.col("doc_id") / DOC_BLOCK)).join(blocks.select("block"), "block", "left_semi")
            got = rows.groupBy("doc_id").agg(F.sum("w").alias("w"), F.count("*").alias("n"))
            got = got.filter(F.col("n") == len(terms)) if mode == "and" else got
            return got.orderBy(F.desc("w"), "doc_id").limit(k).select("doc_id", "w")

        head = best(bounds.orderBy(F.desc("most"), "block").limit(first)).collect()
        threshold = head[-1].w if len(head) == k else -1
        return best(bounds.filter(F.col("most") >= threshold))


def top_k(result: DataFrame, k: int = 10) -> DataFrame:
    """(rk, doc_id, w): greatest weights first, ties by document."""
    rows = result.orderBy(F.desc("w"), "doc_id").limit(k)
    return rows.withColumn("rk", F.row_number().over(W.partitionBy(F.lit(0)).orderBy(F.desc("w"), "doc_id"))).select("rk", "doc_id", "w")


def postings_touched(index: RankedIndex, q: DataFrame) -> DataFrame:
    return q.select(F.explode("terms").alias("term")).join(index.terms(), "term").agg(F.sum("df").alias("touched"))
