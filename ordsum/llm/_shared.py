"""What the operators share: reading inputs, durable intermediate tables, learning folds.

Every operator picks the columns it needs by name, so further columns, also ones
named like an operator's own results, pass through untouched or are left out.
"""

from __future__ import annotations

import re

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ordsum.sources import scratch

LETTER = re.compile(r"[^\W\d_]")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_path(spark: SparkSession, label: str) -> str:
    return scratch.place(spark, label)


def durable(df: DataFrame, label: str) -> DataFrame:
    """Writes df to the shared folder and reads it back: lost executors cost no recomputation."""
    return Scratch().durable(df, label)


class Scratch:
    """Intermediate tables of one computation, which can be deleted once its result is written."""

    def __init__(self):
        self.paths: list[tuple[SparkSession, str]] = []

    def durable(self, df: DataFrame, label: str) -> DataFrame:
        spark, path = df.sparkSession, scratch_path(df.sparkSession, label)
        df.write.parquet(path)
        self.paths.append((spark, path))
        return spark.read.schema(df.schema).parquet(path)

    def drop(self, keep: int = 0) -> None:
        """Deletes all but the last `keep` tables, through Hadoop's file system, wherever they lie."""
        gone, self.paths = self.paths[: len(self.paths) - keep], self.paths[len(self.paths) - keep :]
        for spark, p in gone:
            path = spark._jvm.org.apache.hadoop.fs.Path(p)
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def fold(doc_id: Column, folds: int) -> Column:
    """crc32 of the id as text, modulo the number of folds."""
    return F.crc32(doc_id.cast("string").cast("binary")) % folds


def rank_key(doc_id: Column) -> Column:
    """A fixed pseudo-random order of documents, for bounded training samples."""
    return F.xxhash64(F.lit("sample"), doc_id)


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-np.clip(x, -35, 35)))


class WordIds(dict):
    """Word -> hash, each distinct word hashed once; forgets all when it holds too many."""

    def __init__(self, of, most: int = 400_000):
        super().__init__()
        self.of, self.most = of, most

    def __missing__(self, word):
        if len(self) >= self.most:
            self.clear()
        self[word] = value = self.of(word)
        return value
