"""A training corpus from raw documents, stage by stage.

Each stage takes the documents that the one before it kept and its decisions take
effect; all but the last give back the columns of documents. `run` writes each stage's
result to the shared folder and reads it again for the next.

Cases: rows without an id, and rows that share one, are told apart by a number written
beside them, so of exact copies one stays whatever their ids, and a row goes for its own
text only; null and empty texts pass all stages that judge by content, as the classifier
allows; empty tables give no rows; columns other than those of documents are dropped.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ordsum.llm import decontaminate, jaccard, packing, quality, spans
from ordsum.llm._shared import durable, table

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: A document scoring below this is rejected.
QUALITY = 0.3
ORACLE_SQL = None  # models and tilings have no SQL; the stages are tested against brute force


def numbered(docs: DataFrame) -> DataFrame:
    """docs with a column `row` that is theirs alone: the id where ids are, else a number written once."""
    docs = docs.select(*COLUMNS)
    unclear = docs.groupBy("doc_id").count().filter("count > 1 or doc_id is null").limit(1).count()
    return durable(docs.withColumn("row", F.monotonically_increasing_id()), "numbered") if unclear else docs.withColumn("row", F.col("doc_id").cast("long"))


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier rejects go."""
    model = quality.train(docs, table(spark, sf_dir, "labels"))
    return quality.with_score(docs.select(*COLUMNS), model).filter(F.col("quality_score") >= QUALITY).select(*COLUMNS)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies (five-word shingles, similarity 0.8 or more) the smallest id stays."""
    rows = numbered(docs)
    kept = jaccard.classes(rows.select(F.col("row").alias("doc_id"), "text"), width=5, percent=80).filter("doc_id = component_id")
    return rows.join(kept.select(F.col("doc_id").alias("row")), "row", "left_semi").select(*COLUMNS)


def span_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeated sentence spans are cut; a document of which nothing is left goes."""
    cut = spans.without_repeats(docs.select(*COLUMNS)).filter("n_removed = 0 or length(trim(text)) > 0")
    length = F.when(F.col("n_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))
    return cut.withColumn("n_chars", length).select(*COLUMNS)


def decontaminate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold benchmark items go."""
    rows = numbered(docs)
    found = decontaminate.contaminated(rows.select(F.col("row").alias("doc_id"), "text"), table(spark, sf_dir, "benchmark"))
    return rows.join(durable(found.select(F.col("doc_id").alias("row")).distinct(), "contaminated"), "row", "left_anti").select(*COLUMNS)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces of all documents, packed into sequences."""
    return packing.op5_packing(docs)


STAGES = [
    ("quality classifier", quality_stage),
    ("n-gram Jaccard join", near_duplicate_stage),
    ("substring dedup", span_stage),
    ("benchmark decontamination", decontaminate_stage),
    ("best-fit packing", packing_stage),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = durable(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
