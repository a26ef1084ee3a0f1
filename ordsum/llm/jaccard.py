"""Exact n-gram Jaccard join by prefix filters under several global orders.

A document is the set of its distinct word shingles. With `T = ceil(t * n)` shingles that
a partner must share at least, two linked sets share a token among the first
`n - T + 1` of each under *any* global order of tokens, so the filters of several orders
may be intersected before a pair is verified. All orders put rare tokens first.

1. Equal sets become one unit. Its key is a 64-bit digest; a second digest and the size are
   compared for all documents of a key, and if any two differ all is done again with other
   digests, so two sets are taken for equal only if they agree in 128 bits and in size.
2. Frequencies over all units: hashed shingles travel packed, by hash bucket; only those
   that two units share come back. A unit of which fewer than T are shared has no link.
3. Each survivor meets one pivot per order (a unit that shares its prefix tokens), which
   joins dense groups by few pairs instead of all.
4. Then the pairs that share a prefix token and lie in different components so far. They
   meet only in neighbouring bands of size, of which a link's two sets never lie further apart.
5. Of 3 and 4 alike, the pairs that don't share a prefix token under every order are
   dropped and the others verified. What is left is joined already: components are exact.

Cases: null, empty and wordless texts have no shingle and no link, and are their own
component; fewer words than a shingle make one token of the whole sequence; repeated rows
and repeated ids are equal sets; an empty table gives no rows.

Tokens are hashes of shingles, exchanged as their bucket (8 bits at least, 16 at most) and 40
further bits, so a link could only differ through a collision inside one pair of sets: for
two sets of a thousand shingles about one in 10^8 of one false common shingle.
"""

from __future__ import annotations

import math
import pickle
import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._shared import Scratch, WordIds
from .components import components

ORDERS = 3
WORD = re.compile(r"[^\x20\x09-\x0D]+")
_LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
_M = np.uint64(0x9E3779B97F4A7C15)
_KEEP = np.uint64((1 << 40) - 1)
#: Bytes of packed shingles that a task holds at once. Buckets that would be larger are dealt out again by 16.
HELD = 32 << 20


def _word(w: str) -> int:
    return xxhash.xxh64_intdigest(w.encode("utf-8", "surrogatepass"))


def shingles(text: str | None, width: int, ids: WordIds) -> np.ndarray:
    """Sorted hashes of the distinct shingles."""
    words = WORD.findall(text.translate(_LOWER)) if text else []
    if not words:
        return np.zeros(0, np.uint64)
    t = np.fromiter(map(ids.__getitem__, words), np.uint64, len(words))
    k = min(width, len(t))
    h = t[: len(t) - k + 1] + np.uint64(k)
    for j in range(1, k):
        h = (h ^ (h >> np.uint64(29))) * _M + t[j : len(t) - k + 1 + j]
    h = (h ^ (h >> np.uint64(32))) * _M
    return np.unique(h ^ (h >> np.uint64(31)))


def set_key(s: np.ndarray, seed: int = 0) -> int:
    return xxhash.xxh3_64_intdigest(s.tobytes(), seed) - (1 << 63)


def shared_tokens(docs: DataFrame, width: int, bits: int, rounds: int = 0, seed: int = 0) -> DataFrame:
    """(key, token, df, second): the tokens that at least two units have, df counting units; 2^bits buckets,
    each dealt out by 16 again as many times as there are further rounds.

    Rows with df <= 0 are documents: token is the id, -df the size of the set, key null if that is 0, and
    second another digest of the set."""
    low = np.uint64((1 << bits) - 1)

    def spread(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = WordIds(_word)
        done: set[int] = set()
        for batch in batches:
            for part in (batch.slice(i, 1024) for i in range(0, batch.num_rows, 1024)):
                sets, keys, every = [], [], []
                for i, t in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    s = shingles(t, width, ids)
                    k = set_key(s, seed) if len(s) else None
                    every.append((k, i, -len(s), set_key(s, seed + 1_000_003)))
                    if len(s) and k not in done:
                        if len(done) < 200_000:
                            done.add(k)
                        sets.append(s), keys.append(k)
                at = -1 - int(xxhash.xxh32_intdigest(repr(every[0]).encode())) % int(low + 1)
                yield pa.RecordBatch.from_arrays([pa.array([at], pa.int32()), pa.array([pickle.dumps(every)], pa.binary()), pa.array([b""], pa.binary())], names=["bucket", "k", "v"])
                if not sets:
                    continue
                h = np.concatenate(sets)
                who = np.repeat(np.arange(len(sets), dtype=np.uint16), [len(s) for s in sets])
                bucket = (h & low).astype(np.int64)
                order = np.argsort(bucket, kind="stable")
                h, who, bucket = (h >> np.uint64(bits))[order] & _KEEP, who[order], bucket[order]
                cut = np.flatnonzero(np.r_[True, np.diff(bucket) != 0, True])
                names = np.array(keys, np.int64)
                out_b, out_k, out_v = [], [], []
                for a, b in zip(cut[:-1], cut[1:]):
                    w, x = who[a:b], h[a:b]
                    begin = np.flatnonzero(np.r_[True, np.diff(w) != 0])
                    count = np.diff(np.r_[begin, len(w)])
                    if count.max() > 255:  # a count is one byte: longer runs go as several
                        begin = np.concatenate([np.arange(i, i + c, 255) for i, c in zip(begin, count)])
                        count = np.diff(np.r_[begin, len(w)])
                    out_b.append(int(bucket[a]))
                    out_k.append(names[w[begin]].tobytes() + count.astype(np.uint8).tobytes())
                    out_v.append((x & np.uint64(0xFFFFFFFF)).astype(np.uint32).tobytes() + (x >> np.uint64(32)).astype(np.uint8).tobytes())
                yield pa.RecordBatch.from_arrays([pa.array(out_b, pa.int32()), pa.array(out_k, pa.binary()), pa.array(out_v, pa.binary())], names=["bucket", "k", "v"])

    def meet(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # rows come sorted by bucket; one bucket is held at a time
        held: list[tuple[bytes, bytes]] = []
        at = None
        for batch in batches:
            for b, k, v in zip(*(c.to_pylist() for c in batch.columns)):
                if b != at and held:
                    yield from _bucket(at, held, bits + 4 * rounds)
                    held = []
                at = b
                if b < 0:
                    yield pa.RecordBatch.from_arrays([pa.array(c, x) for c, x in zip(zip(*pickle.loads(k)), (pa.int64(), pa.int64(), pa.int32(), pa.int64()))], names=TOKENS)
                else:
                    held.append((k, v))
        if held:
            yield from _bucket(at, held, bits + 4 * rounds)

    packed = docs.mapInArrow(spread, "bucket int, k binary, v binary")
    for r in range(rounds):
        packed = packed.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(_finer(bits + 4 * r), "bucket int, k binary, v binary")
    return packed.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(meet, "key long, token long, df int, second long")


TOKENS = ["key", "token", "df", "second"]


def _finer(bits: int):
    """Deals each bucket's rows out to 16 by the next four bits of their tokens, as much at once as a task may hold."""

    def emit(bucket: int, rows: list[tuple[bytes, bytes]]) -> pa.RecordBatch:
        key, token = _unpacked(rows)
        part = (token & np.uint64(15)).astype(np.int64)
        out = []
        for x in range(16):
            mine = part == x
            if mine.any():
                k, t = key[mine], token[mine] >> np.uint64(4)
                order = np.argsort(k, kind="stable")
                out.append((bucket | x << bits, *_packed(k[order], t[order])))
        return pa.RecordBatch.from_arrays([pa.array(c, kind) for c, kind in zip(zip(*out), (pa.int32(), pa.binary(), pa.binary()))], names=["bucket", "k", "v"])

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[bytes, bytes]] = []
        at, size = None, 0
        for batch in batches:
            for b, k, v in zip(*(c.to_pylist() for c in batch.columns)):
                if held and (b != at or size > HELD):
                    yield emit(at, held)
                    held, size = [], 0
                at = b
                if b < 0:
                    yield pa.RecordBatch.from_arrays([pa.array([b], pa.int32()), pa.array([k], pa.binary()), pa.array([v], pa.binary())], names=["bucket", "k", "v"])
                else:
                    held.append((k, v))
                    size += len(k) + len(v)
        if held:
            yield emit(at, held)

    return run


def _packed(key: np.ndarray, token: np.ndarray) -> tuple[bytes, bytes]:
    """Units and their tokens, lying together by unit: 8 bytes and a count a run of 255 at most, and 5 bytes a token."""
    begin = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
    count = np.diff(np.r_[begin, len(key)])
    if count.max() > 255:
        begin = np.concatenate([np.arange(i, i + c, 255) for i, c in zip(begin, count)])
        count = np.diff(np.r_[begin, len(key)])
    return key[begin].tobytes() + count.astype(np.uint8).tobytes(), (token & np.uint64(0xFFFFFFFF)).astype(np.uint32).tobytes() + (token >> np.uint64(32)).astype(np.uint8).tobytes()


def _unpacked(rows: list[tuple[bytes, bytes]]) -> tuple[np.ndarray, np.ndarray]:
    keys, tokens = [], []
    for k, v in rows:
        n, m = len(k) // 9, len(v) // 5
        keys.append(np.repeat(np.frombuffer(k, np.int64, n), np.frombuffer(k, np.uint8, n, 8 * n)))
        tokens.append(np.frombuffer(v, np.uint32, m).astype(np.uint64) | np.frombuffer(v, np.uint8, m, 4 * m).astype(np.uint64) << np.uint64(32))
    return np.concatenate(keys), np.concatenate(tokens)


def _bucket(bucket: int, rows: list[tuple[bytes, bytes]], bits: int) -> Iterator[pa.RecordBatch]:
    """The shared tokens of one bucket."""
    key, token = _unpacked(rows)
    order = np.argsort(token, kind="stable")
    key, token = key[order], token[order]
    # a token met once is done with; the others are few
    same = np.r_[False, token[1:] == token[:-1]]
    keep = same | np.r_[same[1:], False]
    key, token = key[keep], token[keep]
    if not len(key):
        return
    order = np.lexsort((key, token))
    key, token = key[order], token[order]
    once = np.r_[True, (token[1:] != token[:-1]) | (key[1:] != key[:-1])]
    key, token = key[once], token[once]
    begin = np.flatnonzero(np.r_[True, token[1:] != token[:-1]])
    df = np.repeat(np.diff(np.r_[begin, len(token)]), np.diff(np.r_[begin, len(token)]))
    key, token, df = key[df > 1], token[df > 1], df[df > 1]
    full = (token << np.uint64(bits) | np.uint64(bucket)).view(np.int64)
    for a in range(0, len(key), 50_000):
        part = slice(a, a + 50_000)
        yield pa.RecordBatch.from_arrays([pa.array(key[part]), pa.array(full[part]), pa.array(df[part].astype(np.int32)), pa.nulls(len(key[part]), pa.int64())], names=TOKENS)


def need(n, percent: int):
    """ceil(percent * n / 100) as a column or number."""
    return F.floor((n * percent + 99) / F.lit(100)) if not isinstance(n, int) else -(-n * percent // 100)


def links(docs: DataFrame, width: int, percent: int, bits: int | None = None, rounds: int | None = None, seed: int = 0) -> tuple[DataFrame, DataFrame]:
    """(units with doc_id, n, key) and (key, component key) of all units that have a link."""
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("t"))
    if bits is None:  # about a million shingles a bucket, so that one fits any task; more than 2^16 buckets come about in rounds
        total = (src.agg(F.sum(F.length("t")).alias("s")).first().s or 0) // 6
        want = max(8, int(total // 1_000_000).bit_length())
        bits, rounds = min(16, want), max(0, -(-(want - 16) // 4)) if rounds is None else rounds
    scratch = Scratch()
    met = scratch.durable(shared_tokens(src, width, bits, rounds or 0, seed), "shared")
    durable = (rest := Scratch()).durable
    shared, units = met.filter("df > 1"), met.filter("df <= 0").select(F.col("token").alias("doc_id"), (-F.col("df")).cast("long").alias("n"), "key", "second")
    unlike = units.filter("key is not null").groupBy("key").agg(F.min("n").alias("a"), F.max("n").alias("b"), F.min("second").alias("c"), F.max("second").alias("d")).filter("a <> b or c <> d")
    if unlike.limit(1).count():  # two different sets have one key
        scratch.drop()
        return links(docs, width, percent, bits, rounds, seed + 1)
    units = units.drop("second")
    sizes = units.filter("key is not null").groupBy("key").agg(F.min("n").alias("n"))
    alive = shared.groupBy("key").agg(F.count("*").alias("k")).join(sizes, "key").withColumn("need", need(F.col("n"), percent).cast("int")).filter("k >= need")
    alive = durable(alive.select("key", "n", "k", (F.col("k") - F.col("need") + 1).cast("int").alias("slots")), "alive")
    # tokens of a survivor: as many as its text has words at most
    sets = durable(shared.join(alive, "key").groupBy("key", "n", "k", "slots").agg(F.collect_list(F.struct("df", "token")).alias("x")), "sets")
    firsts = []
    for r in range(ORDERS):
        # order 0 by exact frequency, the others by its power of two; ties by a hash of their own
        step = "d.df" if r == 0 else "cast(floor(log2(d.df)) as int)"
        ranked = f"array_sort(transform(x, d -> struct({step} as a, xxhash64({r}, d.token) as b, d.token as token)))"
        firsts.append(F.expr(f"transform(slice({ranked}, 1, slots), d -> d.token)").alias(f"p{r}"))
    central = F.expr("aggregate(x, 0D, (s, d) -> s + d.df) / n").alias("central")
    prefixes = durable(sets.select("key", "n", "k", central, *firsts), "prefixes")

    def rows_of(df: DataFrame, r: int, *more: str) -> DataFrame:
        """A row for each prefix token; rest: shared tokens from it on, the most that two sets first met here share."""
        return df.select("key", "n", "k", *more, F.posexplode(f"p{r}").alias("at", "token")).withColumn("rest", F.col("k") - F.col("at")).drop("at", "k")

    def possible(n1: str, r1: str, n2: str, r2: str):
        """Lengths and positions allow a link: both sets have the least overlap left after a first common token."""
        return F.expr(f"{100 + percent}L * least({r1}, {r2}) >= {percent}L * ({n1} + {n2}) and 100L * least({n1}, {n2}) >= {percent}L * greatest({n1}, {n2})")

    def verified(pairs: DataFrame, label: str) -> DataFrame:
        """The pairs (a, b) that are linked. First those go that share no prefix token under one of the orders."""
        p = prefixes.select("key", *[f"p{r}" for r in range(ORDERS)])
        for side in "ab":
            pairs = pairs.join(p.select(F.col("key").alias(side), *[F.col(f"p{r}").alias(f"{side}{r}") for r in range(ORDERS)]), side)
        for r in range(ORDERS):
            pairs = pairs.filter(F.arrays_overlap(f"a{r}", f"b{r}"))
        pairs = durable(pairs.select("a", "b"), label)
        s = sets.select("key", "n", F.col("x.token").alias("s"))
        left = pairs.join(s.select(F.col("key").alias("a"), F.col("n").alias("na"), F.col("s").alias("sa")), "a")
        both = left.join(s.select(F.col("key").alias("b"), F.col("n").alias("nb"), F.col("s").alias("sb")), "b")
        common = F.size(F.array_intersect("sa", "sb"))
        return both.withColumn("c", common).filter(F.expr(f"100L * c >= {percent}L * (na + nb - c)")).select("a", "b")

    # one pivot per unit and order: of its buckets' heads the one it meets most often. Heads are the
    # units of commonest tokens (near the middle of a group of copies), of fewest lone ones, or any
    pivots = None
    for r, best_of in enumerate(("central", "k / n", f"xxhash64({ORDERS}, key)")):
        rows = rows_of(prefixes.withColumn("score", F.expr(f"cast({best_of} as double)")), r, "score")
        heads = rows.groupBy("token").agg(F.max(F.struct("score", "key", "n", "rest")).alias("h"), F.count("*").alias("m")).filter("m > 1")
        heads = durable(heads.select("token", F.col("h.key").alias("pivot"), F.col("h.n").alias("pn"), F.col("h.rest").alias("pr")), f"heads{r}")
        seen = rows.join(heads, "token").filter(F.col("pivot") != F.col("key")).filter(possible("n", "rest", "pn", "pr")).groupBy("key", "pivot").count()
        best = seen.groupBy("key").agg(F.max(F.struct("count", "pivot"))["pivot"].alias("b")).select(F.col("key").alias("a"), "b")
        pivots = best if pivots is None else pivots.unionByName(best)
    pivots = pivots.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    sure = durable(verified(pivots, "pivots"), "sure")
    first = components(sure)

    # every pair across components: in each bucket the units outside its largest component meet all others
    placed = prefixes.join(first.withColumnRenamed("node", "key"), "key", "left").withColumn("component", F.coalesce("component", "key"))
    placed = durable(placed, "placed")
    rows = rows_of(placed, 0, "component")
    per = rows.groupBy("token", "component").count()
    mixed = per.groupBy("token").agg(F.max(F.struct("count", "component"))["component"].alias("main"), F.count("*").alias("parts")).filter("parts > 1").select("token", "main")
    mixed = durable(mixed, "mixed")
    rows = durable(rows.join(mixed, "token"), "mixed_rows")
    # sets whose sizes differ by more than the threshold allows lie two bands apart or more
    band = F.floor(F.log(F.col("n").cast("double")) / F.lit(math.log(100 / percent) * 1.000001 if percent < 100 else 1e-9)).cast("long")
    others = rows.filter("component <> main").select("token", F.col("key").alias("o"), F.col("component").alias("oc"), F.col("n").alias("on_"), F.col("rest").alias("orest"), F.explode(F.array(*[band + x for x in (-1, 0, 1)])).alias("band"))
    pairs = rows.withColumn("band", band).hint("merge").join(others, ["token", "band"]).filter("component <> oc").filter("component = main or key < o").filter(possible("n", "rest", "on_", "orest"))
    pairs = pairs.select(F.least("key", "o").alias("a"), F.greatest("key", "o").alias("b")).distinct()
    more = durable(verified(pairs, "pairs"), "more")
    found = components(sure.unionByName(more))
    rest.drop()
    return units, found


def classes(docs: DataFrame, width: int = 4, percent: int = 85) -> DataFrame:
    """(doc_id, n_shingles, component_id): the smallest doc_id reachable by links, for every row."""
    units, found = links(docs, width, percent)
    heads = units.filter("key is not null").groupBy("key").agg(F.min("doc_id").alias("least"))
    grouped = heads.join(found.withColumnRenamed("node", "key"), "key", "left").withColumn("component", F.coalesce("component", "key"))
    lowest = grouped.groupBy("component").agg(F.min("least").alias("component_id"))
    named = grouped.join(lowest, "component").select("key", "component_id")
    out = units.join(named, "key", "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))


def op8_jaccard(docs: DataFrame) -> DataFrame:
    return classes(docs)
