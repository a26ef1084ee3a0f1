"""Versions of a map on disk: parquet blocks, shared between versions, and a table of blocks per version.

The block table holds, for each block, the key it begins at, its least and greatest entry,
its number of rows, its summary and its file, in the columns' own types. A snapshot reads
that table alone (at most `MOST_BLOCKS` rows); rows are read when an operation opens blocks.

A commit writes the files of changed blocks and the new block table, then renames a finished
manifest to `versions/<n>` without overwriting: of two writers one succeeds, the other gets
`ConflictError`, reads the new head and tries again. Readers hold a version number and never
see a later one or half a manifest. Everything goes through Hadoop's file system, so the
store may lie wherever Spark reads; it must be one whose rename does not replace a file.

After an update, blocks of more than twice `block_rows` rows are split and those of less than
half of it are joined to a neighbour (under the priority policy a block begins where its
keys' hashes say). Other blocks keep their files.
"""

from __future__ import annotations

import json
import uuid
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ordsum.functions.monoids import Monoid
from ordsum.operators.maps import Backing, Base, Conflict, Layout, SummaryMap, _merged, block_of
from ordsum.sources.scratch import rename_new

VALUE = ("block", "cut", "lo", "lov", "hi", "hiv", "n", "a", "file")


class ConflictError(RuntimeError):
    pass


@dataclass
class VersionStore:
    spark: SparkSession
    path: str
    layout: Layout = Layout()
    monoid: Monoid | None = None  # that of the committed maps; a store opened anew must be told
    base: Base | None = None

    def __post_init__(self) -> None:
        self._jvm = self.spark._jvm
        self._conf = self.spark._jsc.hadoopConfiguration()
        self._fs = self._p("").getFileSystem(self._conf)

    def _p(self, name: str):
        return self._jvm.org.apache.hadoop.fs.Path(f"{self.path.rstrip('/')}/{name}")

    def versions(self) -> list[int]:
        at = self._p("versions")
        names = [s.getPath().getName() for s in self._fs.listStatus(at)] if self._fs.exists(at) else []
        return sorted(int(n) for n in names if n.isdigit())

    def head(self) -> int:
        return max(self.versions(), default=-1)

    def manifest(self, version: int) -> dict:
        text = self.spark.read.text(f"{self.path}/versions/{version}", wholetext=True).first().value
        return json.loads(text)

    def _publish(self, version: int, manifest: dict) -> None:
        """The manifest is written whole under another name and then renamed; an existing version is never replaced."""
        self._fs.mkdirs(self._p("versions"))
        aside = self._p(f"versions/new-{uuid.uuid4().hex}")
        out = self._fs.create(aside, False)
        out.write(bytearray(json.dumps(manifest).encode()))
        out.close()
        if not rename_new(self.spark, f"{self.path}/versions/{aside.getName()}", f"{self.path}/versions/{version}"):
            self._fs.delete(aside, False)
            raise ConflictError(f"version {version} exists")

    # ---- writing

    def _write(self, rows: DataFrame, monoid, base: Base, each: int = 1) -> DataFrame:
        """Writes rows (k, v, block) once, a file for each block or for `each` neighbours, and gives the blocks' entries,
        read from the files."""
        folder = f"data/{uuid.uuid4().hex}"
        out = rows.select("k", "v", "block")
        if each > 1:
            out = out.withColumn("file", F.floor(F.col("block") / each).cast("int")).repartition("file").sortWithinPartitions("file", "block", "k")
            out.write.partitionBy("file").parquet(f"{self.path}/{folder}")
            schema = T.StructType([*out.select("k", "v").schema.fields, T.StructField("block", T.IntegerType()), T.StructField("file", T.IntegerType())])
        else:
            out.repartition("block").sortWithinPartitions("block", "k").write.partitionBy("block").parquet(f"{self.path}/{folder}")
            schema = T.StructType([*out.select("k", "v").schema.fields, T.StructField("block", T.IntegerType())])
        written = self.spark.read.schema(schema).parquet(f"{self.path}/{folder}")
        a = monoid.fold(F.col("k"), base(F.col("k"), F.col("v")).cast(monoid.dtype)) if monoid else F.lit(0).cast("bigint")
        got = written.groupBy("block").agg(F.min("k").alias("lo"), F.min_by("v", "k").alias("lov"), F.max("k").alias("hi"), F.max_by("v", "k").alias("hiv"), F.count("*").alias("n"), a.alias("a"))
        at = F.concat(F.lit(f"{folder}/file="), F.floor(F.col("block") / each).cast("string")) if each > 1 else F.concat(F.lit(f"{folder}/block="), F.col("block").cast("string"))
        return got.withColumn("file", at)

    def _kinds(self, rows: DataFrame, a: T.DataType) -> T.StructType:
        k, v = rows.schema["k"].dataType, rows.schema["v"].dataType
        kinds = (T.IntegerType(), k, k, v, k, v, T.LongType(), a, T.StringType())
        return T.StructType([T.StructField(n, kind) for n, kind in zip(VALUE, kinds)])

    def _put_table(self, infos: list[tuple], kinds: T.StructType) -> str:
        name = f"blocks/{uuid.uuid4().hex}"
        self.spark.createDataFrame(infos, kinds).coalesce(1).write.parquet(f"{self.path}/{name}")
        return name

    def commit(self, m: SummaryMap, tag=None, files: int | None = None) -> int:
        """A whole map, with its monoid's block summaries, as the next version. With `files`, neighbouring blocks share
        a file where there would be more of them than that; such a version is read only."""
        self.monoid, self.base = m.monoid, m.base
        each = 1 if files is None else -(-(len(m.splitters) + 1) // files)
        got = self._write(m.rows, m.monoid, m.base, each)
        found = {r.block: r for r in got.collect()}  # bounded by the number of blocks
        cuts = [None, *m.splitters]
        rows = [self._info(b, cut, found.get(b)) for b, cut in enumerate(cuts)]
        table = self._put_table(rows, self._kinds(m.rows, got.schema["a"].dataType))
        v = self.head() + 1
        self._publish(v, {"schema": m.rows.select("k", "v").schema.json(), "table": table, "monoid": m.monoid.name if m.monoid else None, "many": m.many, "each": each, "tags": self._tags({}, tag)})
        return v

    @staticmethod
    def _info(block: int, cut, r) -> tuple:
        return (block, cut, None, None, None, None, 0, None, None) if r is None else (block, cut, r.lo, r.lov, r.hi, r.hiv, r.n, r.a, r.file)

    @staticmethod
    def _tags(tags: dict, tag) -> dict:
        """A tag is a name, or the name of a series and a number that only grows: of a series the last number is kept."""
        if tag is None:
            return tags
        name, number = tag if isinstance(tag, tuple) else (tag, 0)
        return tags | {name: max(number, tags.get(name, number))}

    @staticmethod
    def _applied(tags: dict, tag) -> bool:
        name, number = tag if isinstance(tag, tuple) else (tag, 0)
        return tag is not None and name in tags and number <= tags[name]

    # ---- reading

    def snapshot(self, version: int | None = None, monoid=None, base: Base | None = None) -> SummaryMap:
        """A version as a map. Another monoid than the store's may be asked for; its summaries are then made from rows."""
        own = monoid is None
        monoid, base = (self.monoid, self.base) if own else (monoid, base)
        man = self.manifest(self.head() if version is None else version)
        table = self.spark.read.parquet(f"{self.path}/{man['table']}")
        infos = table.orderBy("block").collect()
        splitters = [r.cut for r in infos[1:]]
        schema = T.StructType.fromJson(json.loads(man["schema"]))
        files = {r.block: r.file for r in infos if r.n}
        each = man.get("each", 1)

        def rows(blocks: list) -> DataFrame:
            paths = sorted({f"{self.path}/{files[b]}" for b in blocks if b in files})
            if not paths:
                return self.spark.createDataFrame([], T.StructType([*schema.fields, T.StructField("block", T.IntegerType())]))
            if each > 1:
                out = self.spark.read.schema(T.StructType([*schema.fields, T.StructField("block", T.IntegerType())])).parquet(*paths)
                return out if len(blocks) == len(infos) else out.filter(_among(sorted(blocks)))
            out = self.spark.read.schema(schema).parquet(*paths)
            return out.withColumn("block", F.lit(blocks[0]).cast("int") if len(paths) == len(blocks) == 1 else block_of(F.col("k"), splitters).cast("int"))

        backing = Backing(infos, table, rows, own and monoid is not None and monoid.name == man["monoid"])
        return SummaryMap(rows([r.block for r in infos]), splitters, monoid, base or (lambda k, v: v), self.layout, backing, man.get("many", False))

    # ---- updates

    def insert_many(self, batch: DataFrame, h: Conflict | None = None, tries: int = 5, base: int | None = None, tag=None) -> int:
        """Only the blocks that the batch's keys fall in are read and written; others are shared.

        `tag` makes a batch idempotent: what a version knows of is not applied again."""
        batch = batch.select("k", "v")
        return self._update(lambda m, blocks: _merged(m.opened(blocks), batch, h, m.many), batch, tries, base, tag)

    def delete_many(self, keys: DataFrame, tries: int = 5, tag=None) -> int:
        keys = keys.select("k")
        return self._update(lambda m, blocks: m.opened(blocks).join(keys, "k", "left_anti").select("k", "v"), keys, tries, None, tag)

    def _update(self, change, keys: DataFrame, tries: int, base: int | None, tag) -> int:
        for k in range(tries):
            v = self.head() if base is None or k else base
            man = self.manifest(v)
            if self._applied(man["tags"], tag):
                return v
            if man.get("each", 1) > 1:
                raise ValueError("blocks of this version share files: it is read only")
            if (self.monoid.name if self.monoid else None) != man["monoid"]:
                raise ValueError(f"the store keeps summaries of {man['monoid']}")
            m = self.snapshot(v)
            touched = m.touched(keys)
            table = self._rebuilt(m, touched, change(m, touched))
            try:
                self._publish(v + 1, man | {"table": table, "tags": self._tags(man["tags"], tag)})
                return v + 1
            except ConflictError:
                if k + 1 == tries:
                    raise
        raise ConflictError("no try left")

    def _rebuilt(self, m: SummaryMap, touched: list[int], rows: DataFrame) -> str:
        """The block table after `rows` have taken the place of the touched blocks' rows; blocks are kept in their sizes."""
        infos = m.stored.infos
        kinds = m.rows.schema
        # the changed rows are written once; they are read again only where blocks must be cut anew
        staged = f"{self.path}/staged/{uuid.uuid4().hex}"
        rows.select(F.col("k").cast(kinds["k"].dataType), F.col("v").cast(kinds["v"].dataType)).withColumn("block", block_of(F.col("k"), m.splitters).cast("int")).write.parquet(staged)
        changed = self.spark.read.parquet(staged)
        counts = {r.block: r["count"] for r in changed.groupBy("block").count().collect()}
        hit = set(touched)
        size = [counts.get(r.block, 0) if r.block in hit else r.n for r in infos]
        cuts, again = self._cuts(m, size, changed, hit)
        # blocks that keep their bounds and were not touched keep their entry
        old = {(infos[b].cut, infos[b + 1].cut if b + 1 < len(infos) else None): infos[b] for b in range(len(infos)) if b not in again}
        bounds = list(zip(cuts, [*cuts[1:], None]))
        more = sorted(again.difference(touched))
        fresh = changed.unionByName(m.opened(more)) if more else changed
        inner = cuts[1:]
        got = self._write(fresh.select("k", "v", block_of(F.col("k"), inner).cast("int").alias("block")), m.monoid, m.base)
        found = {r.block: r for r in got.collect()}
        out = []
        for b, pair in enumerate(bounds):
            kept = old.get(pair)
            out.append(tuple([b, *kept[1:]]) if kept is not None else self._info(b, pair[0], found.get(b)))
        self._fs.delete(self._jvm.org.apache.hadoop.fs.Path(staged), True)
        return self._put_table(out, self._kinds(m.rows, got.schema["a"].dataType))

    def _cuts(self, m: SummaryMap, size: list[int], changed: DataFrame, touched: set[int]) -> tuple[list, set]:
        """Where blocks begin from now on (None first), and the old blocks whose rows must be written anew."""
        infos, again = m.stored.infos, set(touched)
        if self.layout.policy == "priority":
            opens = [r.k for r in changed.filter(self.layout.opens(sum(size))).select("k").collect()]
            stay = [r.cut for r in infos[1:] if r.block not in touched]
            # a block that began at a deleted key is joined to the one before it, which is written anew
            cuts = sorted({*stay, *opens})
            for r in infos[1:]:
                if r.block in touched and r.cut not in cuts:
                    again.add(max(x.block for x in infos[: r.block]))
            first_of = {None, *cuts}
            for r in infos[1:]:
                if r.cut not in first_of:
                    again.update((r.block, r.block - 1))
            return [None, *cuts], again
        least, most = self.layout.sizes()
        big = [b for b in touched if size[b] > most]
        parts: dict[int, list] = {}
        if big:  # a sample of their keys by hash, at a fixed rate: about 32 for each block they will make
            rate = max(1, self.layout.block_rows // 32)
            sample = changed.filter(F.col("block").isin(big) & (F.pmod(F.xxhash64("k"), F.lit(rate)) == 0)).select("block", "k").collect()
            for r in sample:
                parts.setdefault(r.block, []).append(r.k)
        cuts: list = []
        run, rows = [], 0  # neighbours that will be one block
        for r in infos:
            n = size[r.block]
            if run and (rows >= least and n >= least or rows + n > most):
                run, rows = [], 0
            if run:
                again.update((run[-1], r.block))
            else:
                cuts.append(r.cut)
            run.append(r.block)
            rows += n
            if r.block in parts:
                keys = sorted(parts[r.block])
                want = self.layout.wanted(n)
                inner = sorted({keys[len(keys) * i // want] for i in range(1, want)})
                cuts += [k for k in inner if r.cut is None or k > r.cut]
                run, rows = [r.block], n // max(1, want)
        return cuts, again

    def expire(self, keep: int) -> int:
        """Forgets all but the last `keep` versions and deletes the files that only they had."""
        versions = self.versions()
        old, live = versions[:-keep], versions[-keep:]
        used, tables = self._files(live)
        gone, gone_tables = self._files(old)
        for v in old:
            self._fs.delete(self._p(f"versions/{v}"), False)
        for f in [*(gone - used), *(gone_tables - tables)]:
            self._fs.delete(self._p(f), True)
        return len(gone - used)

    def replace_private(self, m: SummaryMap) -> int:
        """The next version, for a writer that knows of no other reader: what only older ones had is deleted."""
        v = self.commit(m)
        self.expire(1)
        return v

    def _files(self, versions: list[int]) -> tuple[set, set]:
        tables = {self.manifest(v)["table"] for v in versions}
        if not tables:
            return set(), set()
        read = self.spark.read.parquet(*[f"{self.path}/{t}" for t in tables])
        return {r.file for r in read.filter("n > 0").select("file").distinct().collect()}, tables

    def sharing(self, versions: list[int]) -> tuple[int, int, float]:
        """(blocks without sharing, blocks there are, share saved)."""
        files = [r.file for v in versions for r in self.spark.read.parquet(f"{self.path}/{self.manifest(v)['table']}").filter("n > 0").select("file").collect()]
        return len(files), len(set(files)), 1 - len(set(files)) / max(1, len(files))


def _among(blocks: list) -> Column:
    """Whether column block is one of a sorted list, by its runs of neighbours."""
    runs: list = []
    for b in blocks:
        if runs and runs[-1][1] == b - 1:
            runs[-1][1] = b
        else:
            runs.append([b, b])
    return reduce(lambda x, y: x | y, [F.col("block").between(*r) for r in runs]) if len(runs) <= 16 else F.col("block").isin(blocks)


_KEPT: dict = {}
#: Files of a map that is kept for reading.
MOST_FILES = 512


def kept(spark: SparkSession, path: str, name: tuple, make) -> SummaryMap:
    """The map of that name in this session, built and committed at `path` the first time it is asked for."""
    key = (spark.sparkContext.applicationId, name)
    if key not in _KEPT:
        m = make()
        store = VersionStore(spark, path, m.layout)
        store.commit(m, files=MOST_FILES)
        _KEPT[key] = store.snapshot()
    return _KEPT[key]
