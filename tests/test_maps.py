import random

import pytest
from pyspark.sql import Row
from pyspark.sql import functions as F

from ordsum.functions import monoids as M
from ordsum.operators import batch as R
from ordsum.operators.intervals import IntervalMap, stab_pairs
from ordsum.operators.maps import Layout, SummaryMap, concat, link, union
from ordsum.sources.store import ConflictError, VersionStore
from ordsum.workloads import ALL
from tests.harness import DATA, compare, views

HAND = [(1, 10), (3, 30), (5, 50), (7, 70), (9, 90)]


def make(spark, rows=HAND, monoid=None, rows_per=2, policy="count", **kw):
    return SummaryMap.build(spark.createDataFrame(rows, "k bigint, v bigint"), "k", "v", monoid or M.sum_(), layout=Layout(policy, rows_per, 2), **kw)


def test_hand_map(spark):
    m = make(spark)
    one = lambda df: [tuple(r) for r in df.collect()]
    assert one(m.rank(5)) == [(2,)] and one(m.select(2)) == [(5, 50)] and one(m.select(9)) == []
    assert one(m.summary_range(3, 7)) == [(150,)] and one(m.summary_range(3, 7, "()")) == [(50,)] and one(m.summary_range(7, 3)) == [(0,)]
    assert one(m.summary_left(5, False)) == [(40,)] and one(m.summary_left(5)) == [(90,)]
    assert one(m.find(4)) == [] and one(m.next(5)) == [(7, 70)] and one(m.prev(1)) == []
    low, mid, high = m.split(5)
    assert sorted(one(concat(low, high).entries())) == [x for x in HAND if x[0] != 5] and one(mid) == [(5, 50)]
    assert sorted(one(link(low, 5, 50, high).entries())) == HAND
    with pytest.raises(ValueError):
        link(high, 5, 50, low)
    assert one(m.insert(5, 1, lambda old, new: old - new).find(5)) == [(5, 49)] and one(m.find(5)) == [(5, 50)]


def test_empty_maps(spark):
    e = SummaryMap.empty(spark, monoid=M.sum_())
    assert e.summary().first().a == 0 and e.first().count() == 0 and e.size().first().n == 0
    assert sorted(tuple(r) for r in union(e, make(spark)).entries().collect()) == HAND


def test_build_variants(spark):
    df = spark.createDataFrame([(2, "b", 0), (1, "a", 1), (2, "c", 2), (2, "d", 3)], "k bigint, v string, t int")
    first = SummaryMap.build(df, "k", "v", tie=["t"]).entries().collect()
    fold = SummaryMap.build(df, "k", "v", h=lambda x, y: F.concat(x, y), tie=["t"]).entries().collect()
    assert {tuple(r) for r in first} == {(1, "a"), (2, "b")} and {tuple(r) for r in fold} == {(1, "a"), (2, "bcd")}
    nulls = spark.createDataFrame([(None, 1), (4, 2)], "k bigint, v bigint")
    assert SummaryMap.build(nulls, "k", "v", null_keys="drop").entries().count() == 1
    with pytest.raises(Exception, match="null key"):
        SummaryMap.build(nulls, "k", "v").entries().collect()


def test_strategies_agree_with_a_fold(spark):
    rng = random.Random(3)
    rows = [(k, rng.randrange(-50, 50)) for k in rng.sample(range(300), 90)]
    qs = [(i, *[rng.randrange(-10, 310) for _ in range(2)]) for i in range(40)]
    q = spark.createDataFrame(qs, "qid bigint, lo bigint, hi bigint")
    inside = lambda lo, hi: [v for k, v in sorted(rows) if lo <= k <= hi]
    for policy in ("count", "fanout", "fill", "priority"):
        m = make(spark, rows, rows_per=3, policy=policy)
        for s in ("prefix", "canonical"):
            got = dict(map(tuple, R.range_summaries(m, q, s).collect()))
            assert got == {i: sum(inside(lo, hi)) for i, lo, hi in qs}, (policy, s)
    top = make(spark, rows, M.max_(), rows_per=3)
    for s in ("overlap", "canonical"):
        got = dict(map(tuple, R.range_summaries(top, q, s).collect()))
        assert got == {i: max(inside(lo, hi), default=None) for i, lo, hi in qs}, s
    aff = M.affine()
    m = make(spark, rows, aff, rows_per=3, base=lambda k, v: F.struct((F.abs(v) + 1).alias("p"), F.abs(v).alias("q")))
    got = {r.qid: tuple(r.a) for r in R.range_summaries(m, q).collect()}
    for i, lo, hi in qs:
        want = (1, 0)
        for v in inside(lo, hi):
            want = aff.of(want, (abs(v) + 1, abs(v)))
        assert got[i] == want


def test_guards():
    values = list(range(-5, 6))
    M.check_or_homomorphic(lambda a: a > 2, M.max_(), values)
    with pytest.raises(ValueError):
        M.check_or_homomorphic(lambda a: a < 2, M.max_(), values)
    with pytest.raises(ValueError):
        M.check_distributes(lambda a: a, M.sum_(), M.max_(), values)
    M.check_distributes(len, M.custom("cat", "string", "", None, of=lambda a, b: a + b), M.sum_(), ["", "a", "bc"])
    for m, vs in ((M.sum_(), values), (M.max_(), values), (M.concat(","), ["", "a", "b"]), (M.affine(), [(2, 1), (3, 0), (1, 5)]), (M.top_k(2), [[3, 1], [2], []])):
        M.check_laws(m, vs)


def test_intervals(spark):
    iv = [(0, 1, 4), (1, 2, 9), (2, 2, 3), (3, -7, -5), (4, 6, 6), (5, 9, 12)]
    m = IntervalMap.build(spark.createDataFrame(iv, "id bigint, lo bigint, hi bigint"), Layout(block_rows=2))
    pts = spark.createDataFrame([(p, p) for p in range(-9, 14)], "pid bigint, p bigint")
    want = {(p, i) for p in range(-9, 14) for i, lo, hi in iv if lo < p < hi}
    assert {(r.pid, r.id) for r in stab_pairs(m.source, pts).collect()} == want
    assert {r.pid for r in m.stab_many(pts).filter("covered").collect()} == {p for p, _ in want}
    counts = dict(map(tuple, m.count_many(pts).collect()))
    assert all(counts[p] == sum(x == p for x, _ in want) for p in range(-9, 14))
    assert m.report_by_extraction(2) == [1] and sorted(r.id for r in m.report(2).collect()) == [0]


def test_store_versions(spark, tmp_path):
    st = VersionStore(spark, str(tmp_path), Layout(block_rows=2))
    st.commit(make(spark))
    add = lambda k, v: spark.createDataFrame([(k, v)], "k bigint, v bigint")
    v1 = st.insert_many(add(4, 40))
    assert st.insert_many(add(9, 1), lambda old, new: old + new, base=0) == 2  # the loser of a race tries again on the new head
    assert {tuple(r) for r in st.snapshot(0).entries().collect()} == set(HAND)
    assert {tuple(r) for r in st.snapshot().entries().collect()} == {*HAND[:4], (4, 40), (9, 91)}
    assert st.sharing([0, v1])[2] > 0
    with pytest.raises(ConflictError):
        st._publish(v1, {})
    assert st.insert_many(add(8, 8), tag="x") == st.insert_many(add(8, 8), tag="x")
    assert st.insert_many(add(6, 60), tag=("s", 4)) == 4 and st.insert_many(add(6, 61), tag=("s", 3)) == 4
    assert st.delete_many(add(6, 0)) == 5
    st.expire(1)
    assert st.versions() == [5] and st.snapshot().size().first().n == 7


STORED = [(k, 7 * k % 31 - 9) for k in range(0, 60, 2)]


@pytest.fixture(scope="module")
def stored(spark, tmp_path_factory):
    st = VersionStore(spark, str(tmp_path_factory.mktemp("store")), Layout(block_rows=4, fanout=2))
    st.commit(make(spark, STORED, rows_per=4))
    return st


def files_read(df):
    """Data files that a plan reads."""
    return {f.rsplit("/data/", 1)[1] for f in df.inputFiles() if "/data/" in f}


def test_stored_summaries_open_cut_blocks_only(spark, stored):
    m = stored.snapshot()
    blocks = len(m.splitters) + 1
    assert blocks >= 6
    for lo, hi, bounds in ((5, 41, "[]"), (4, 40, "()"), (8, 8, "[]"), (50, 3, "[]"), (-5, 100, "[]"), (0, 58, "(]")):
        inside = sum(v for k, v in STORED if (lo <= k if bounds[0] == "[" else lo < k) and (k <= hi if bounds[1] == "]" else k < hi))
        got = m.summary_range(lo, hi, bounds)
        assert got.first().a == inside and len(files_read(got)) <= 2
    assert not files_read(m.summary()) and m.summary().first().a == sum(v for _, v in STORED)
    assert m.summary_left(11).first().a == sum(v for k, v in STORED if k <= 11) and len(files_read(m.summary_left(11))) <= 1
    assert m.summary_right(11, False).first().a == sum(v for k, v in STORED if k > 11)
    row = lambda df: [tuple(r) for r in df.collect()]
    for df, want in ((m.first(), STORED[:1]), (m.last(), STORED[-1:]), (m.next(11), [(12, STORED[6][1])]), (m.next(58), []), (m.prev(12), [STORED[5]]), (m.prev(0), []), (m.find(12), [STORED[6]]),
                     (m.find(13), []), (m.select(0), STORED[:1]), (m.select(17), [STORED[17]]), (m.select(30), []), (m.rank(13), [(7,)]), (m.rank(-1), [(0,)]), (m.rank(99), [(30,)]), (m.size(), [(30,)])):
        assert row(df) == want and len(files_read(df)) <= 1
    q = spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate([(-3, 7), (5, 41), (60, 70), (9, 2), (0, 58)])], "qid bigint, lo bigint, hi bigint")
    want = {r.qid: sum(v for k, v in STORED if r.lo <= k <= r.hi) for r in q.collect()}
    for strategy in ("prefix", "canonical", "few"):
        assert dict(row(R.range_summaries(m, q, strategy))) == want
    assert R.explain_choice(m, q)[0] == "few" and R.explain_choice(m, spark.range(200).selectExpr("id as qid", "id as lo", "id as hi"))[0] == "prefix"
    assert sorted(row(m.range(5, 41).entries())) == [x for x in STORED if 5 <= x[0] <= 41]
    assert m.decompose()[1].first().k == 30


def test_stored_filter_reads_the_blocks_that_qualify(spark, tmp_path):
    rows = [(k, 1000 if k in (7, 41) else k % 5) for k in range(64)]
    st = VersionStore(spark, str(tmp_path), Layout(block_rows=8))
    st.commit(make(spark, rows, M.max_(), 8))
    got = st.snapshot().summary_filter(lambda a: a > 100).entries()
    assert sorted(map(tuple, got.collect())) == [(7, 1000), (41, 1000)] and len(files_read(got)) == 2
    both = M.product(hi=M.max_(), lo=M.min_())
    st.commit(make(spark, rows, both, 8, base=lambda k, v: F.struct(v.alias("hi"), v.alias("lo"))))
    got = st.snapshot().summary_filter(lambda a: a["hi"] >= 0, lambda a: a["lo"] >= 0)
    assert got.entries().count() == 64


@pytest.mark.parametrize("policy", ["count", "fill", "fanout", "priority"])
def test_blocks_keep_their_size(spark, tmp_path, policy):
    """After many inserts and deletes: the same rows and summaries as a map built at once, and blocks within bounds."""
    st = VersionStore(spark, str(tmp_path), Layout(policy, 64, 4))
    st.commit(SummaryMap.build(spark.range(100).select(F.col("id").alias("k"), F.col("id").alias("v")), "k", "v", M.sum_(), layout=st.layout))
    some = lambda a, b, step=1: spark.range(a, b, step).select(F.col("id").alias("k"), (F.col("id") * 3).alias("v"))
    st.insert_many(some(1000, 6000))
    st.insert_many(some(0, 400), lambda old, new: old + new)
    v = st.delete_many(some(1500, 5900))
    want = {k: k * 4 if k < 100 else k * 3 for k in [*range(400), *range(1000, 1500), *range(5900, 6000)]}
    m = st.snapshot()
    assert dict(map(tuple, m.entries().collect())) == want and m.summary().first().a == sum(want.values())
    infos = m.stored.infos
    assert [i.block for i in infos] == list(range(len(infos))) and [i.cut for i in infos[1:]] == sorted(i.cut for i in infos[1:])
    for i in infos:
        inside = sorted(k for k in want if (i.cut is None or i.cut <= k) and (i.block + 1 == len(infos) or k < infos[i.block + 1].cut))
        assert i.n == len(inside) and (not inside or (i.lo, i.hi, i.a) == (inside[0], inside[-1], sum(want[k] for k in inside)))
    if policy == "priority":  # equal contents, equal blocks
        built = SummaryMap.build(m.entries(), "k", "v", layout=st.layout)
        assert built.splitters == m.splitters
    else:
        assert all(i.n <= 2 * 64 + 32 for i in infos) and sum(i.n < 32 for i in infos) <= 1
    before = st.sharing([v])[0]
    v2 = st.insert_many(some(5990, 5991))
    assert st.sharing([v, v2])[1] <= before + 2  # the touched block, and a neighbour at most, are new


def test_stored_keys_of_any_kind(spark, tmp_path):
    import datetime

    day = [datetime.date(2024, 1, 1) + datetime.timedelta(days=i) for i in range(20)]
    for n, keys in enumerate((day, [f"key {i:02}" for i in range(20)], [Row(a=i // 3, b=f"x{i:02}") for i in range(20)])):
        st = VersionStore(spark, str(tmp_path / str(n)), Layout(block_rows=4))
        st.commit(SummaryMap.build(spark.createDataFrame([(k, i) for i, k in enumerate(keys)], "k struct<a:bigint,b:string>, v bigint" if n == 2 else None).toDF("k", "v"), "k", "v", M.sum_(), layout=st.layout))
        m = st.snapshot()
        assert m.summary_range(keys[3], keys[11]).first().a == sum(range(3, 12)) and m.rank(keys[7]).first().r == 7
        one = spark.createDataFrame([(keys[5], 500)], m.rows.select("k", "v").schema)
        st.insert_many(one)
        assert st.snapshot().find(keys[5]).first().v == 500


def test_union_keeps_the_left_maps_kind(spark):
    many = SummaryMap.build(spark.range(1000).select(F.col("id").alias("k"), F.col("id").alias("v")), "k", "v", layout=Layout(block_rows=50))
    got = union(make(spark), many)
    assert got.monoid.name == "sum" and got.layout == make(spark).layout and got.summary().first().a == sum(range(1000)) - 25 + 250


def test_streams_fold_and_are_told_apart(spark, tmp_path):
    from ordsum.streaming.ingest import ingest

    st = VersionStore(spark, str(tmp_path / "store"))
    st.commit(make(spark))
    for n, rows in enumerate(([(1, 5), (1, 7)], [(3, 1)])):
        folder = str(tmp_path / f"in{n}")
        spark.createDataFrame(rows, "k bigint, v bigint").coalesce(1).write.parquet(folder)
        stream = spark.readStream.schema("k bigint, v bigint").parquet(folder)
        for _ in range(2):  # the second run finds nothing new
            ingest(stream, st, str(tmp_path / f"at{n}"), lambda old, new: old + new).awaitTermination()
    got = dict(map(tuple, st.snapshot().entries().collect()))
    assert got[1] == 10 + 12 and got[3] == 31 and st.snapshot().summary().first().a == 250 + 13


def test_plans_have_no_nested_loops(spark):
    from ordsum.measures import plan_text
    from ordsum.workloads import ALL

    for n in ("sum_range_many_prefix", "sum_range_many_canonical", "iv_stab_many", "rect_sum_many", "idx_batch_top10"):
        text = plan_text(ALL[n][0](spark, "/root/testdata/sf0.001"))
        assert "CartesianProduct" not in text, n
        if n == "sum_range_many_canonical":  # maps of one block join their single bound row
            assert "BroadcastNestedLoopJoin" not in text, n


@pytest.mark.parametrize("cuts", [[-7, 0, 3, 3_000_000_000], ["b", "it's", "z"], [1.5, 2.5], [Row(a=1, b=-2), Row(a=1, b=5), Row(a=4, b=0)], []])
def test_block_of_counts_the_splitters_at_or_below(spark, cuts):
    from bisect import bisect_right

    from ordsum.operators.maps import block_of

    every = [
        ([-8, -7, -1, 3, 4, 3_000_000_000, 1 << 62], "bigint"), (["", "b", "c", "it's", "zz"], "string"), ([1.0, 1.5, 9.0], "double"),
        ([Row(a=0, b=9), Row(a=1, b=5), Row(a=1, b=6), Row(a=9, b=9)], "struct<a:bigint,b:int>"),
    ]
    keys, kind = next(x for x in every if not cuts or type(x[0][0]) is type(cuts[0]))
    rows = spark.createDataFrame([(k,) for k in [*keys, None]], f"k {kind}")
    got = rows.select("k", block_of(F.col("k"), cuts).alias("b")).collect()
    assert [r.b for r in got] == [bisect_right(cuts, k) for k in keys] + [0]


def test_entries_of_one_key_all_stay(spark, tmp_path):
    rows = [(1, 10), (3, 30), (3, 30), (3, 31), (5, 50), (7, 70), (7, 70)]
    m = make(spark, rows, h="all")
    st = VersionStore(spark, str(tmp_path / "many"), m.layout)
    st.commit(m)
    one = lambda df: sorted(tuple(r) for r in df.collect())
    for x in (m, st.snapshot()):
        assert one(x.entries()) == rows and one(x.size()) == [(7,)] and one(x.summary()) == [(291,)] and one(x.rank(5)) == [(4,)]
        assert one(x.summary_range(2, 5)) == [(141,)] and one(x.range(3, 3).entries()) == rows[1:4] and one(x.find(7)) == rows[5:]
        assert one(x.last()) == rows[5:] and one(x.first()) == rows[:1] and one(x.select(3)) == [(3, 31)]
        got = R.select_many(x, spark.range(7).select(F.col("id").alias("i")))
        assert one(got) == [(i, *r) for i, r in enumerate(rows)]
    batch = spark.createDataFrame([(3, 32), (4, 40)], "k bigint, v bigint")
    assert one(m.insert_many(batch).entries()) == sorted([*rows, (3, 32), (4, 40)])
    st.insert_many(batch)
    assert one(st.snapshot().entries()) == sorted([*rows, (3, 32), (4, 40)])


def test_events_of_one_moment_all_stay(spark, tmp_path):
    """Queries over events whose times repeat, beside their SQL."""
    e = spark.read.parquet(f"{DATA}/events.parquet").filter("event_id % 10 = 0")
    again = e.withColumn("event_id", F.col("event_id") + 1_000_001)
    d = str(tmp_path / "data")
    e.unionByName(again).coalesce(1).write.parquet(f"{d}/events.parquet")
    spark.read.parquet(f"{DATA}/customer.parquet").limit(20).coalesce(1).write.parquet(f"{d}/customer.parquet")
    con = views(d)
    for name in "op_first_last op_insert_many op_range op_range_many op_up_to op_down_to op_rank sum_all sum_count sum_moments sum_filter_all sum_project_size sql_summary_range base_bulk_insert st_ingest".split():
        f, sql = ALL[name]
        assert compare(spark, name, f, sql, d, con) == "", name


def test_equal_queries_are_answered_once(spark):
    q = spark.createDataFrame([(1, 2, 5), (2, 2, 5), (3, 9, 1), (4, 2, 5), (5, 1, 9)], "qid bigint, lo bigint, hi bigint")
    seen = []
    got = R.once(q, ["lo", "hi"], lambda each: (seen.append(each.count()), each.select("qid", (F.col("hi") - F.col("lo")).alias("a")))[1], ["a"])
    assert seen == [3] and sorted(tuple(r) for r in got.collect()) == [(1, 3), (2, 3), (3, -8), (4, 3), (5, 8)]
    m = make(spark, monoid=M.max_())
    assert sorted(tuple(r) for r in R.range_summaries(m, q, "overlap").collect()) == [(1, 50), (2, 50), (3, None), (4, 50), (5, 90)]


def test_kept_maps_share_files(spark, tmp_path):
    rows = [(k, k % 7) for k in range(60)]
    m = make(spark, rows)
    st = VersionStore(spark, str(tmp_path / "few"), m.layout)
    st.commit(m, files=4)
    x = st.snapshot()
    one = lambda df: sorted(tuple(r) for r in df.collect())
    assert len(m.splitters) > 20 and len({r.file for r in x.stored.infos}) <= 4
    assert one(x.entries()) == rows and one(x.range(7, 40).entries()) == rows[7:41] and one(x.find(33)) == [rows[33]]
    assert one(x.summary_range(3, 50)) == [(sum(v for _, v in rows[3:51]),)] and one(x.rank(21)) == [(21,)]
    with pytest.raises(ValueError):
        st.insert_many(spark.createDataFrame([(1, 1)], "k bigint, v bigint"))


@pytest.mark.parametrize("most", [1 << 16, 4])
def test_rectangles_of_both_kinds_of_blocks(spark, monkeypatch, most):
    """Values of x as blocks of their own, whose bounds cut none, and, where these are too many, blocks of neighbours."""
    from ordsum.operators import rect

    monkeypatch.setattr(rect, "MOST_BLOCKS", most)
    rng = random.Random(5)
    pts = [(i, rng.randrange(12), rng.randrange(-9, 30), rng.randrange(-20, 20)) for i in range(150)]
    qs = [(i, *sorted(rng.randrange(-2, 15) for _ in range(2)), *sorted(rng.randrange(-12, 34) for _ in range(2))) for i in range(25)] + [(90, 5, 3, 0, 9), (91, 3, 5, 9, 0)]
    r = rect.RectIndex.build(spark.createDataFrame(pts, "id bigint, x bigint, y bigint, w bigint"), Layout(block_rows=32, fanout=2), y_rows=20)
    q = spark.createDataFrame(qs, "qid bigint, xl bigint, xr bigint, yl bigint, yr bigint")
    inside = {i: [(p, w) for p, x, y, w in pts if xl <= x <= xr and yl <= y <= yr] for i, xl, xr, yl, yr in qs}
    sums = {i: sum(w for _, w in ws) for i, ws in inside.items()}
    assert r.exact == (most > 4)
    assert dict(map(tuple, r.sums_many(q).collect())) == sums == dict(map(tuple, r.cover_many(q, M.sum_()).collect()))
    assert dict(map(tuple, r.cover_many(q, M.max_()).collect())) == {i: max((w for _, w in ws), default=None) for i, ws in inside.items()}
    assert sorted(map(tuple, r.list_many(q).collect())) == sorted((i, p) for i, ws in inside.items() for p, _ in ws)


def test_heights_take_part_in_the_join(spark):
    """Intervals far above a point are not among the candidates, let alone the answers."""
    from ordsum.operators import intervals as I

    rng = random.Random(6)
    h = [(i, lo, lo + rng.randrange(0, 40), rng.randrange(-50, 50)) for i in range(80) for lo in [rng.randrange(-60, 60)]]
    v = [(i, rng.randrange(-60, 90), y - 4, y + 3) for i in range(40) for y in [rng.randrange(-50, 50)]]
    hs, vs = spark.createDataFrame(h, "id bigint, lo bigint, hi bigint, y bigint"), spark.createDataFrame(v, "id bigint, x bigint, ylo bigint, yhi bigint")
    want = sorted((a, b) for a, lo, hi, y in h for b, x, l, u in v if lo < x < hi and l <= y <= u)
    assert sorted(map(tuple, I.segments_crossing(hs, vs).collect())) == want
    near = hs.select("id", "lo", "hi", (F.col("y") - 5).alias("ylo"), (F.col("y") + 5).alias("yhi"))
    want = sorted((a, c) for a, al, ah, ay in h for c, cl, ch, cy in h if al <= ch and cl <= ah and abs(ay - cy) <= 5)
    assert sorted(map(tuple, I.overlap_pairs(near, hs).collect())) == want
    want = {b: best[1] for b, x, l, _ in v for best in [max(((y, a) for a, lo, hi, y in h if lo < x < hi and y <= l), default=None)] if best}
    assert dict(map(tuple, I.locate(hs, vs.select(F.col("id").alias("pid"), "x", F.col("ylo").alias("y"))).collect())) == want


def test_streams_of_added_rows_leave_no_table_in_memory(spark):
    before = len(spark.catalog.listTables())
    f, sql = ALL["st_stream_static"]
    assert compare(spark, "st_stream_static", f, sql) == "" and len(spark.catalog.listTables()) == before


def test_what_comes_after_is_one_pass(spark):
    """No frame ends behind its row, where it would be folded anew for each: neighbours, carries, boundary folds."""
    from ordsum.measures import plan_text

    rng = random.Random(8)
    rows = [(rng.randrange(60), rng.randrange(99)) for _ in range(200)]
    m = make(spark, rows, monoid=M.max_(), h="all")
    q = spark.createDataFrame([(i, k) for i, k in enumerate(range(-2, 63))], "qid bigint, k bigint")
    near = R.neighbor_many(m, q, "next")
    ends = spark.createDataFrame([(i, *sorted(rng.randrange(-3, 63) for _ in range(2))) for i in range(40)], "qid bigint, lo bigint, hi bigint")
    most = R.range_summaries(m, ends, "canonical")
    for x in (near, most):
        assert "unboundedfollowing" not in plan_text(x).lower()
    for r in near.collect():
        later = [k for k, _ in rows if k > r.k]
        assert r.nk == min(later, default=None) and (r.nk is None or (r.nk, r.nv) in rows)
    bounds = {r.qid: r for r in ends.collect()}
    for r in most.collect():
        assert r.a == max((v for k, v in rows if bounds[r.qid].lo <= k <= bounds[r.qid].hi), default=None)


def test_points_alike_are_one_row_of_a_level(spark, tmp_path):
    from ordsum.operators.rect import RectIndex

    pts = [(i, i % 3, i % 2, i % 2 + 5) for i in range(600)]
    r = RectIndex.build(spark.createDataFrame(pts, "id bigint, x bigint, y bigint, w bigint"), Layout(block_rows=32, fanout=2)).store(str(tmp_path / "rect"))
    assert r.levels().filter("level = 0").count() == 6
    q = spark.createDataFrame([(1, 0, 1, 1, 1), (2, 0, 2, 0, 1), (3, 1, 1, 4, 9)], "qid bigint, xl bigint, xr bigint, yl bigint, yr bigint")
    inside = {i: [w for _, x, y, w in pts if xl <= x <= xr and yl <= y <= yr] for i, xl, xr, yl, yr in q.collect()}
    of = lambda df: dict(map(tuple, df.collect()))
    sums = {i: sum(ws) for i, ws in inside.items()}
    assert of(r.sums_many(q)) == sums == of(r.cover_many(q, M.sum_())) and of(r.count_many(q)) == {i: len(ws) for i, ws in inside.items()}
    assert of(r.cover_many(q, M.bit_xor())) == {1: 0, 2: 0, 3: 0}
    assert of(r.cover_many(q, M.max_())) == {i: max(ws, default=None) for i, ws in inside.items()}
    assert r.list_many(q).count() == sum(map(len, inside.values()))


def test_postings_travel_once_for_all_queries(spark):
    from ordsum.measures import plan_text
    from ordsum.operators import ranked_index as X

    rng = random.Random(9)
    rows = [(t, d, rng.randrange(50)) for t in "abcde" for d in rng.sample(range(60), 40)]
    index = X.RankedIndex(spark.createDataFrame(rows, "term string, doc_id bigint, w bigint"))
    asked = [(1, ["a", "b"]), (2, ["b", "a", "b"]), (3, ["c", "d", "e"]), (4, ["e"]), (5, ["a", "none"])]
    of = {(t, d): w for t, d, w in rows}
    want = []
    for qid, terms in asked:
        both = [(sum(of[t, d] for t in set(terms)), d) for d in range(60) if all((t, d) in of for t in terms)]
        want += [(qid, i + 1, d, w) for i, (w, d) in enumerate(sorted(both, key=lambda x: (-x[0], x[1]))[:3])]
    q = spark.createDataFrame(asked, "qid bigint, terms array<string>")
    assert sorted(map(tuple, index.search_batch(q, k=3).collect())) == want
    assert "FlatMapGroupsInPandas" in plan_text(index.search_batch(q)) and "Exchange range" not in plan_text(index.clustered())


def test_overlaps_are_counted_without_pairs(spark):
    from ordsum.measures import plan_text
    from ordsum.operators import intervals as I

    rng = random.Random(10)
    some = lambda n: [(i - n // 2, lo, lo + rng.randrange(-2, 12)) for i in range(n) for lo in [rng.randrange(-30, 30)]]
    a, b = some(40), some(60) + [(1000 + i, 3, 8) for i in range(50)]
    met = {x: [y for y, l, h in b if l <= h and l <= hi and lo <= h] for x, lo, hi in a if lo <= hi}
    frame = lambda rows: spark.createDataFrame(rows, "id bigint, lo bigint, hi bigint")
    assert sorted(map(tuple, I.overlap_totals(frame(a), frame(b)).collect())) == sorted((x, len(ys), sum(ys)) for x, ys in met.items() if ys)
    # pairs would meet in cells
    assert "shiftright" in plan_text(ALL["iv_overlap"][0](spark, DATA)) and "shiftright" not in plan_text(ALL["join_interval"][0](spark, DATA))
    assert compare(spark, "join_interval", *ALL["join_interval"]) == ""


def test_nested_loop_holds_equal_intervals_once(spark):
    from ordsum.measures import plan_text
    from ordsum.operators import baselines as B

    rng = random.Random(11)
    rows = [(i, lo, lo + rng.randrange(-1, 9)) for i in range(50) for lo in [rng.randrange(-20, 20)]] + [(i, 2, 7) for i in range(100, 400)]
    points = [(p, p) for p in range(-25, 30)]
    got = B.interval_counts_nlj(spark.createDataFrame(rows, "id bigint, lo bigint, hi bigint"), spark.createDataFrame(points, "pid bigint, p bigint"))
    want = {p: sum(lo < p < hi for _, lo, hi in rows) for p, _ in points}
    assert dict(map(tuple, got.collect())) == {p: n for p, n in want.items() if n}
    text = plan_text(got)
    assert "BroadcastNestedLoopJoin" in text and "keys=[lo" in text
    assert compare(spark, "base_iv_nlj", *ALL["base_iv_nlj"]) == ""


@pytest.mark.parametrize("long", [0, 2])
def test_rectangles_meet_by_heights_alone_where_intervals_are_long(spark, monkeypatch, long):
    from ordsum.measures import plan_text
    from ordsum.operators import intervals as I

    monkeypatch.setattr(I, "LONG", long)
    rng = random.Random(12)
    h = [(i, lo, lo + rng.randrange(-3, 90), rng.randrange(-50, 50)) for i in range(90) for lo in [rng.randrange(-60, 60)]]
    hs = spark.createDataFrame(h, "id bigint, lo bigint, hi bigint, y bigint")
    near = hs.filter("id % 3 = 0").select("id", "lo", "hi", (F.col("y") - 5).alias("ylo"), (F.col("y") + 4).alias("yhi"))
    got = I.overlap_pairs(near, hs)
    ok = [r for r in h if r[1] <= r[2]]
    assert sorted(map(tuple, got.collect())) == sorted((a, c) for a, al, ah, ay in ok if a % 3 == 0 for c, cl, ch, cy in ok if al <= ch and cl <= ah and -5 <= cy - ay <= 4)
    assert ("shiftright" in plan_text(got)) == (long > 1)
    assert I.overlap_pairs(near.filter("id < 0"), hs).count() == 0


def test_rect_overlap_reads_bars_once_written(spark):
    from ordsum.measures import plan_text

    text = plan_text(ALL["rect_overlap"][0](spark, DATA))
    assert "lineitem" not in text and "shiftright" not in text
    assert compare(spark, "rect_overlap", *ALL["rect_overlap"]) == ""


@pytest.mark.parametrize("long", [0, 2])
def test_segments_cross_by_heights_alone_where_they_are_long(spark, monkeypatch, long):
    from ordsum.measures import plan_text
    from ordsum.operators import intervals as I

    monkeypatch.setattr(I, "LONG", long)
    rng = random.Random(13)
    h = [(i, lo, lo + rng.randrange(-2, 80), rng.randrange(-50, 50)) for i in range(80) for lo in [rng.randrange(-60, 60)]]
    v = [(i, rng.randrange(-60, 90), y - 4, y + rng.randrange(-6, 4)) for i in range(40) for y in [rng.randrange(-50, 50)]]
    hs, vs = spark.createDataFrame(h, "id bigint, lo bigint, hi bigint, y bigint"), spark.createDataFrame(v, "id bigint, x bigint, ylo bigint, yhi bigint")
    got = I.segments_crossing(hs, vs)
    assert sorted(map(tuple, got.collect())) == sorted((a, b) for a, lo, hi, y in h for b, x, l, u in v if lo < x < hi and l <= y <= u)
    assert ("shiftright" in plan_text(got)) == (long > 1)


def test_seg_cross_reads_bars_once_written(spark):
    from ordsum.measures import plan_text

    text = plan_text(ALL["seg_cross"][0](spark, DATA))
    assert "lineitem" not in text and "shiftright" not in text
    assert compare(spark, "seg_cross", *ALL["seg_cross"]) == ""


def test_positions_of_repeated_times(spark, tmp_path):
    """Every entry of a moment has a position of its own. Equal times have equal values here: the SQL orders no further."""
    e = spark.read.parquet(f"{DATA}/events.parquet")
    many = [e.withColumn("event_id", F.col("event_id") + i * 1000) for i in range(3)]
    d = str(tmp_path / "data")
    many[0].unionByName(many[1]).unionByName(many[2]).coalesce(1).write.parquet(f"{d}/events.parquet")
    f, sql = ALL["op_select_many"]
    assert compare(spark, "op_select_many", f, sql, d, views(d)) == ""
    assert f(spark, d).filter("k is not null").count() > e.count()


def test_scan_answers_all_ranges_in_one_pass(spark):
    from ordsum.measures import plan_text
    from ordsum.operators import baselines as B

    rng = random.Random(14)
    rows = [(rng.randrange(-40, 40), rng.choice([None, rng.randrange(-9, 9)])) for _ in range(9000)] + [(70, None), (None, 5)]
    asked = [(i, *(rng.randrange(-60, 60) for _ in range(2))) for i in range(60)] + [(90, 70, 70), (91, -5, 9), (92, -5, 9), (93, 41, 69)]
    got = B.scan_range(spark.createDataFrame(rows, "k bigint, v bigint"), spark.createDataFrame(asked, "qid bigint, lo bigint, hi bigint"))
    met = {i: [v for k, v in rows if k is not None and v is not None and lo <= k <= hi] for i, lo, hi in asked}
    assert dict(map(tuple, got.collect())) == {i: sum(vs) if vs else None for i, vs in met.items()}
    assert "BroadcastNestedLoopJoin" not in plan_text(got)
    f, sql = ALL["base_scan_range"]
    assert compare(spark, "base_scan_range", f, sql) == "" and f(spark, DATA).count() == spark.read.parquet(f"{DATA}/events.parquet").count()


def test_rectangles_of_all_orders_are_scanned(spark):
    from ordsum.measures import plan_text
    from ordsum.operators import baselines as B

    rng = random.Random(15)
    pts = [(i, rng.randrange(-20, 20), rng.randrange(-30, 30), rng.randrange(-5, 9)) for i in range(200)]
    qs = [(i, x, x + rng.randrange(-2, 9), y, y + rng.randrange(-2, 30)) for i in range(60) for x, y in [(rng.randrange(-25, 20), rng.randrange(-35, 30))]] + [(90, 0, 9, 0, 9), (91, 0, 9, 0, 9)]
    p, q = spark.createDataFrame(pts, "id bigint, x bigint, y bigint, w bigint"), spark.createDataFrame(qs, "qid bigint, xl bigint, xr bigint, yl bigint, yr bigint")
    inside = {i: [(n, w) for n, x, y, w in pts if xl <= x <= xr and yl <= y <= yr] for i, xl, xr, yl, yr in qs}
    assert sorted(map(tuple, B.rect_scan(p, q).collect())) == sorted((i, n, w) for i, ws in inside.items() for n, w in ws)
    got = B.rect_sums_scan(p, q)
    assert dict(map(tuple, got.collect())) == {i: sum(w for _, w in ws) for i, ws in inside.items() if ws}
    assert "BroadcastNestedLoopJoin" not in plan_text(got)
    f, sql = ALL["base_rect_scan"]
    assert compare(spark, "base_rect_scan", f, sql) == "" and f(spark, DATA).filter("qid % 50 <> 0").count()


@pytest.mark.parametrize("most", [1 << 16, 3])
def test_points_are_located_without_stabbings(spark, monkeypatch, most):
    from ordsum.measures import plan_text
    from ordsum.operators import intervals as I

    monkeypatch.setattr(I, "MOST_BLOCKS", most)
    rng = random.Random(16)
    h = [(i, lo, lo + rng.randrange(-2, 60), rng.randrange(-9, 9)) for i in range(120) for lo in [rng.randrange(-60, 60)]] + [(-5, -900, 900, -8)]
    p = [(i, rng.randrange(-70, 130), rng.randrange(-12, 12)) for i in range(150)] + [(900, 5, 3), (901, 5, 3)]
    hs, ps = spark.createDataFrame(h, "id bigint, lo bigint, hi bigint, y bigint"), spark.createDataFrame(p, "pid bigint, x bigint, y bigint")
    below = {i: max(((hy, n) for n, lo, hi, hy in h if lo < x < hi and hy <= y), default=None) for i, x, y in p}
    want = {i: b[1] for i, b in below.items() if b}
    got = I.locate(hs, ps)
    assert dict(map(tuple, got.collect())) == want
    assert dict(map(tuple, I.locate(hs, ps.filter("pid < 9")).collect())) == {i: n for i, n in want.items() if i < 9}
    assert "lo < p" not in (text := plan_text(got)) and "Window" in text
    assert I.locate(hs, ps.filter("pid < 0")).count() == 0 == I.locate(hs.filter("id = 999"), ps).count()
    assert compare(spark, "pt_locate", *ALL["pt_locate"]) == ""


def test_a_sample_for_bounds_sends_the_driver_what_is_wanted(spark, monkeypatch):
    """Of few distinct keys among many rows all take part in the end; of many only a share of the hashes."""
    many = spark.range(0, 40_000).select((F.col("id") * 7).alias("k"))
    by_hash = [r.k for r in many.orderBy(F.xxhash64("k")).limit(640).collect()]
    seen, kind = [], type(many)
    collect = kind.collect
    monkeypatch.setattr(kind, "collect", lambda df: (seen.append(df._jdf.queryExecution().optimizedPlan().toString()), collect(df))[1])
    cuts = Layout(block_rows=2000).splitters(many)
    assert cuts == sorted({sorted(by_hash)[640 * i // 20] for i in range(1, 20)}) and "Filter" in seen[0]
    few = many.filter("k < 700").withColumn("c", F.lit(400))
    assert len(Layout(block_rows=4000).splitters(few, 40_000)) == 9


def test_covers_read_what_was_written_once(spark):
    from ordsum.measures import plan_text

    for name in ("rect_max_many", "rect_sum_cover"):
        assert "/covered-" in (text := plan_text(ALL[name][0](spark, DATA))) and "/levels" not in text, name
    assert compare(spark, "rect_sum_cover", *ALL["rect_sum_cover"]) == "" == compare(spark, "rect_max_many", *ALL["rect_max_many"])
