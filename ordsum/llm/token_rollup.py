"""Token counts as delta-maintained rollups.

A batch is a table of signed changes: `insert` adds a document's count, `delete` takes its
old count away, `revise` does both. Changes are pre-aggregated to additive deltas by
source, language and tokenizer version, and one batch is one commit: its deltas are
written aside and renamed to `deltas/<batch id>` in one step, which never replaces a name
that is taken. A batch id that is there already is not applied again, so replays and
retries after a failure change nothing.

Totals are sums of deltas; `compact` folds committed batches into one delta that carries
their names. Totals leave out what a fold names, so the rename of the fold is the one step
in which it takes the batches' place; deleting them afterwards only frees space.

A tokenizer version is a vocabulary file of a public tokenizer, or a rule in DataFrame
functions.

Cases: null source or language is a group of its own; null text has no tokens but is a
document; an empty batch commits nothing but its name; repeated rows count as often as
they come; deletes may arrive before their inserts, since sums commute; keys of zero
documents and tokens vanish from totals; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ordsum.sources.scratch import rename_new

from ._shared import durable, scratch_path
from .vocabulary import encoder, in_parts

KEYS = ("source", "lang", "tokenizer")
DELTA = "source string, lang string, tokenizer string, docs long, tokens long"


def white_space_words(text: Column) -> Column:
    """Runs of characters other than the six ASCII white-space ones."""
    parts = F.split(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+")
    return F.size(F.filter(parts, lambda x: x != "")).cast("long")


def utf8_quads(text: Column) -> Column:
    """A rule of thumb in use for byte-level vocabularies: one token per four bytes, rounded up."""
    return F.ceil(F.coalesce(F.octet_length(text), F.lit(0)) / F.lit(4)).cast("long")


def words_with_letters(text: Column) -> Column:
    """White-space words that hold an ASCII letter or digit."""
    parts = F.split(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+")
    return F.size(F.filter(parts, lambda x: x.rlike("[A-Za-z0-9]"))).cast("long")


RULES = {"words-1": white_space_words, "words-2": words_with_letters, "bytes-1": utf8_quads}
#: Vocabulary files of byte-level public tokenizers, by version.
VOCABULARIES = {"byte_bpe_50k": "byte_bpe_50k.json", "byte_bpe_multi_50k": "byte_bpe_multi_50k.tiktoken"}
#: Words that a task remembers of each vocabulary.
REMEMBERED = 250_000


def counted(docs: DataFrame, versions: Iterable[str] = ("byte_bpe_50k", "bytes-1")) -> DataFrame:
    """(doc_id, source, lang, tokenizer, tokens): one row per document and tokenizer version, in one pass over the texts."""
    rules = [v for v in versions if v in RULES]
    files = {v: VOCABULARIES[v] for v in versions if v not in RULES}
    count = [F.struct(F.lit(k).alias("tokenizer"), RULES[k](F.col("text")).alias("tokens")) for k in rules]
    by_rule = F.array(*count) if count else F.array().cast("array<struct<tokenizer:string,tokens:bigint>>")
    src = docs.select("doc_id", F.col("source").cast("string").alias("source"), F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"))
    rows = src.select("doc_id", "source", "lang", "text", by_rule.alias("c"))
    if files:

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                texts, sizes = batch.column(3).to_pylist(), []
                for name in files.values():
                    enc = encoder(name, REMEMBERED)
                    sizes.append(pa.array([len(ids) for _, part in in_parts(texts) for ids in enc.encode(part)], pa.int64()))
                yield pa.RecordBatch.from_arrays([*batch.columns[:3], batch.column(4), *sizes], names=[*batch.schema.names[:3], "c", *(f"n{k}" for k in range(len(files)))])
            for name in files.values():  # the worker lives on, with other stages' memory
                encoder(name, REMEMBERED).forget()

        kind = rows.schema["doc_id"].dataType.simpleString()
        schema = f"doc_id {kind}, source string, lang string, c array<struct<tokenizer:string,tokens:bigint>>" + "".join(f", n{k} bigint" for k in range(len(files)))
        rows = rows.mapInArrow(run, schema)
        found = F.array(*[F.struct(F.lit(v).alias("tokenizer"), F.col(f"n{k}").alias("tokens")) for k, v in enumerate(files)])
        rows = rows.withColumn("c", F.concat("c", found))
    return rows.select("doc_id", "source", "lang", F.explode("c").alias("c")).select("doc_id", "source", "lang", "c.tokenizer", "c.tokens")


def inserts(counts: DataFrame) -> DataFrame:
    return counts.select(*KEYS, F.lit(1).cast("long").alias("docs"), "tokens")


def deletes(counts: DataFrame) -> DataFrame:
    return counts.select(*KEYS, F.lit(-1).cast("long").alias("docs"), (-F.col("tokens")).alias("tokens"))


def revisions(old: DataFrame, new: DataFrame) -> DataFrame:
    return deletes(old).unionByName(inserts(new))


class Rollup:
    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")
        self._path = spark._jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(self.path).getFileSystem(spark._jsc.hadoopConfiguration())

    def _names(self) -> list[str]:
        top = self._path(f"{self.path}/deltas")
        return sorted(s.getPath().getName() for s in self._fs.listStatus(top)) if self._fs.exists(top) else []

    def _folded(self) -> set[str]:
        """Batches that some fold has taken in."""
        out: set[str] = set()
        for name in self._names():
            at = self._path(f"{self.path}/deltas/{name}/_folds")
            if self._fs.exists(at):  # Spark's readers pass over names that begin like this one
                stream = self._fs.open(at)
                out.update(self.spark._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8").split("\n"))
                stream.close()
        return out

    def batches(self) -> list[str]:
        """The deltas that totals are made of."""
        gone = self._folded()
        return [n for n in self._names() if n not in gone]

    def commit(self, batch_id: str, changes: DataFrame, folds: Iterable[str] = ()) -> bool:
        """Applies the signed changes once. False if the batch had been committed before."""
        if batch_id in self._folded() or batch_id in self._names():
            return False
        aside = f"{self.path}/aside/{batch_id}-{scratch_path(self.spark, 'x').rsplit('-', 1)[1]}"
        sums = changes.groupBy(*KEYS).agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens"))
        sums.coalesce(1).write.parquet(aside)
        if folds:
            out = self._fs.create(self._path(f"{aside}/_folds"), False)
            out.write(bytearray("\n".join(sorted(folds)).encode()))
            out.close()
        self._fs.mkdirs(self._path(f"{self.path}/deltas"))
        if not rename_new(self.spark, aside, f"{self.path}/deltas/{batch_id}"):
            self._fs.delete(self._path(aside), True)
            return False
        return True

    def totals(self) -> DataFrame:
        names = self.batches()
        if not names:
            return self.spark.createDataFrame([], DELTA)
        rows = self.spark.read.schema(DELTA).parquet(*[f"{self.path}/deltas/{b}" for b in names])
        sums = rows.groupBy(*KEYS).agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens"))
        return sums.filter("docs <> 0 or tokens <> 0")

    def compact(self, into: str) -> bool:
        """Folds all committed batches into one delta; their names stay known as committed."""
        names = self.batches()
        if not self.commit(into, self.totals(), {*names, *self._folded()}):
            return False
        self.sweep()
        return True

    def sweep(self) -> None:
        """Deletes deltas that a fold has taken in (but for their names)."""
        gone = self._folded()
        for b in self._names():
            if b in gone and not self._fs.exists(self._path(f"{self.path}/deltas/{b}/_folds")):
                self._fs.delete(self._path(f"{self.path}/deltas/{b}"), True)


def op3_rollup(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Every document comes in, counted by one vocabulary and by bytes; those labelled of low quality are deleted;
    the vocabulary's counts are revised to those of another; one batch is replayed and all are folded."""
    spark = docs.sparkSession
    roll = Rollup(spark, scratch_path(spark, "rollup"))
    old, new = VOCABULARIES
    # one pass over the texts; what meets the labels afterwards are counts, not texts
    counts = durable(counted(docs, (old, new, "bytes-1")), "counts")
    bad = labels.filter("quality = 0").select("doc_id").distinct()
    first = counts.filter(F.col("tokenizer") != new)
    kept = counts.join(bad, "doc_id", "left_anti")
    roll.commit("load", inserts(first))
    gone = deletes(first.join(bad, "doc_id", "left_semi"))
    roll.commit("low-quality", gone)
    roll.commit("revised", revisions(kept.filter(F.col("tokenizer") == old), kept.filter(F.col("tokenizer") == new)))
    roll.commit("low-quality", gone)
    roll.compact("folded")
    return roll.totals()
