"""Folders for tables that outlive one query: below spark.checkpoint.dir, which all executors of a cluster share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_OWN: list[str] = []
_TABLES: dict = {}


def root(spark: SparkSession) -> str:
    """The shared folder of the session. Where none is named, a local session gets a folder of this process, deleted at its end."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    if not _OWN:
        _OWN.append(tempfile.mkdtemp(prefix="ordsum-"))
        atexit.register(shutil.rmtree, _OWN[0], True)
    return _OWN[0]


def place(spark: SparkSession, label: str) -> str:
    return f"{root(spark)}/{label}-{uuid.uuid4().hex[:12]}"


def kept(spark: SparkSession, name: tuple, make) -> DataFrame:
    """A table written once in this session, the first time it is asked for."""
    key = (spark.sparkContext.applicationId, name)
    if key not in _TABLES:
        path = place(spark, str(name[0]))
        make().write.parquet(path)
        _TABLES[key] = path
    return spark.read.parquet(_TABLES[key])


def rename_new(spark: SparkSession, source: str, target: str) -> bool:
    """Moves a file or folder to a name that nothing has yet; False, and nothing moved, if it is taken."""
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    a, b = (jvm.org.apache.hadoop.fs.Path(x) for x in (source, target))
    fs = a.getFileSystem(conf)
    a, b = fs.makeQualified(a), fs.makeQualified(b)
    kind = getattr(jvm.org.apache.hadoop.fs, "Options$Rename")
    try:
        jvm.org.apache.hadoop.fs.FileContext.getFileContext(fs.getUri(), conf).rename(a, b, spark.sparkContext._gateway.new_array(kind, 0))
    except Exception:
        if fs.exists(b):
            return False
        raise
    return True
