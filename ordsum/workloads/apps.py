"""Queries over intervals, rectangles, the ranked index, the store and streams, with their SQL."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from ordsum.functions import monoids as M
from ordsum.operators import baselines as B
from ordsum.operators import intervals as I
from ordsum.operators import ranked_index as X
from ordsum.operators.batch import once
from ordsum.operators.maps import Layout, SummaryMap
from ordsum.operators.rect import RectIndex
from ordsum.sources import scratch
from ordsum.sources import tables as S

DAY = S.DAY
IV = "iv as (select o_orderkey as id, epoch_us(least(o_orderdate, s)) as lo, epoch_us(greatest(o_orderdate, s)) as hi from orders join (select l_orderkey, max(l_shipdate) as s from lineitem group by 1) on o_orderkey = l_orderkey)"
PT = "pt as (select distinct epoch_us(o_orderdate) as p from orders)"
SE = """e as (select user_id, epoch_us(ts) as t from events),
f as (select *, case when t - lag(t) over (partition by user_id order by t) <= 21600000000 then 0 else 1 end as nw from e),
g as (select *, sum(nw) over (partition by user_id order by t) as sid from f),
se as (select user_id * 1000000 + sid as id, min(t) as lo, max(t) as hi from g group by user_id, sid)"""
P1 = 883_612_800_000_000  # 1998-01-01
RP = "rp as (select epoch_us(l_shipdate) // 86400000000 as x, cast(round(l_extendedprice*100) as bigint) as y, cast(l_quantity as bigint) as w from lineitem)"
RQ = "rq as (select o_orderkey as qid, epoch_us(o_orderdate) // 86400000000 as xl, epoch_us(o_orderdate) // 86400000000 + 180 as xr, cast(round(o_totalprice*100) as bigint) * 18 // 100 as yl, cast(round(o_totalprice*100) as bigint) * 22 // 100 as yr from orders)"
TOK = r"tok as (select doc_id, unnest(string_split_regex(lower(text), '[^\p{L}\p{N}]+')) as term from documents)"
IDX = TOK + ", idx as (select term, doc_id, count(*) as tf, ('0x' || substr(md5(doc_id::varchar || '|' || term), 1, 8))::bigint % 1000 as w from tok where term <> '' group by 1, 2)"
QA = "fr as (select term from idx group by 1 having count(*) >= 50), qa as (select * from (select doc_id as qid, min(term) as t1, max(term) as t2 from idx where term in (select term from fr) group by 1) where t1 <> t2)"

Q: dict = {}


def add(name: str, f, sql: str | None) -> None:
    Q[name] = (f, sql)


def iv(s, d):
    return I.IntervalMap.build(S.ord_iv(s, d))


def rect(s, d):
    """The rectangle index on disk, built once a session."""
    key = (s.sparkContext.applicationId, d)
    if key not in _RECT:
        t = S.li_pts(s, d)
        _RECT[key] = RectIndex.build(t.withColumn("id", F.xxhash64("id"))).store(scratch.place(s, "rect"))
    return _RECT[key]


_RECT: dict = {}


def built_index(s, d):
    return X.RankedIndex.build(X.weigh(X.tokenize(S.table(s, d, "documents"), "doc_id", "text")))


def index(s, d):
    """The postings on disk, by term and document, written once a session."""
    return X.RankedIndex(scratch.kept(s, ("postings", d), lambda: built_index(s, d).clustered()))


def asked(s, d):
    return scratch.kept(s, ("and-queries", d), lambda: S.q_and(s, d))


# ---- intervals
add("iv_build", lambda s, d: iv(s, d).by_lo.summary(), f"with {IV} select max(hi) as a from iv")
add("iv_stab", lambda s, d: iv(s, d).stab(P1), f"with {IV} select count(*) > 0 as covered from iv where lo < {P1} and {P1} < hi")
STAB = f"with {IV}, {PT} select p as pid, p, exists (select 1 from iv where lo < p and p < hi) as covered from pt"
add("iv_stab_many", lambda s, d: iv(s, d).stab_many(S.iv_points(s, d)), STAB)
add("iv_report", lambda s, d: iv(s, d).report(P1), f"with {IV} select id, lo, hi from iv where lo < {P1} and {P1} < hi")
add("iv_report_many", lambda s, d: iv(s, d).report_many(S.iv_points(s, d)).groupBy("pid").agg(F.count("*").alias("n"), F.sum("id").alias("ids"), F.max("id").alias("last")), f"with {IV}, {PT} select p as pid, count(*) as n, cast(sum(id) as bigint) as ids, max(id) as last from pt join iv on lo < p and p < hi group by 1")
COUNT = f"with {IV}, {PT} select p as pid, cast(count(id) as bigint) as n from pt left join iv on lo < p and p < hi group by 1"
add("iv_count_many", lambda s, d: iv(s, d).count_many(S.iv_points(s, d)), COUNT)
add("iv_insert", lambda s, d: iv(s, d).insert(-1, P1 - 5, P1 + 5).report(P1), f"with {IV} select id, lo, hi from iv where lo < {P1} and {P1} < hi union all select -1, {P1 - 5}, {P1 + 5}")
add("iv_union", lambda s, d: iv(s, d).union(I.IntervalMap.build(S.sess_iv(s, d))).stab_many(S.iv_points(s, d).unionByName(S.ev_map(s, d).select(F.col("k").alias("pid"), F.col("k").alias("p")))), f"with {IV}, {SE}, {PT}, al as (select lo, hi from iv union all select lo, hi from se), pp as (select p from pt union all select epoch_us(ts) from events) select p as pid, p, exists (select 1 from al where lo < p and p < hi) as covered from pp")
add("iv_delete", lambda s, d: iv(s, d).delete(S.ord_iv(s, d).filter("id % 3 = 0").select("id")).stab_many(S.iv_points(s, d)), f"with {IV}, {PT} select p as pid, p, exists (select 1 from iv where lo < p and p < hi and id % 3 <> 0) as covered from pt")
add("op_iv_min_length", lambda s, d: iv(s, d).drop_shorter(300 * DAY), f"with {IV} select id, lo, hi from iv where hi - lo >= {300 * DAY}")
add("iv_overlap", lambda s, d: I.overlap_pairs(S.sess_iv(s, d).filter("hi - lo > 20000000000"), S.sess_iv(s, d).filter("hi > lo")), f"with {SE} select a.id as aid, b.id as bid from se a join se b on a.lo <= b.hi and b.lo <= a.hi where a.hi - a.lo > 20000000000 and b.hi > b.lo")
add("wl_stab_orders", Q["iv_stab_many"][0], STAB)
SPT = "sp as (select distinct epoch_us(ts) as p from events)"
add("wl_stab_sessions", lambda s, d: I.IntervalMap.build(S.sess_iv(s, d)).stab_many(S.ev_map(s, d).select(F.col("k").alias("pid"), F.col("k").alias("p"))), f"with {SE}, {SPT}, r as (select t, sum(x) over (order by t, o) as c from (select lo as t, 1 as x, 2 as o from se where lo < hi union all select hi, -1, 0 from se where lo < hi)) select p as pid, p, exists (select 1 from se where lo < p and p < hi) as covered from sp")
add("wl_report_orders", lambda s, d: iv(s, d).report_many(S.iv_points(s, d)).groupBy("pid").agg(F.count("*").alias("n")), f"with {IV}, {PT} select p as pid, count(*) as n from pt join iv on lo < p and p < hi group by 1")
add("base_iv_nlj", lambda s, d: once(S.searched(S.table(s, d, "orders").select(F.col("o_orderkey").alias("qid"), S.micros("o_orderdate").alias("p"))), ["p"], lambda q: B.interval_counts_nlj(S.ord_iv(s, d), q.withColumnRenamed("qid", "pid")).withColumnRenamed("pid", "qid"), ["n"]).withColumnRenamed("qid", "pid"), f"with {IV} select o_orderkey as pid, count(*) as n from orders join iv on lo < epoch_us(o_orderdate) and epoch_us(o_orderdate) < hi where o_orderkey % 50 = 0 group by 1")

# ---- rectangles
RSUM = f"with {RP}, {RQ} select qid, cast(coalesce(sum(w), 0) as bigint) as a from rq left join rp on x between xl and xr and y between yl and yr group by 1"
one = lambda s: s.createDataFrame([(1, 9862, 10226, 2_000_000, 4_000_000)], "qid bigint, xl bigint, xr bigint, yl bigint, yr bigint")
ONE = "x between 9862 and 10226 and y between 2000000 and 4000000"
add("rect_build", lambda s, d: RectIndex.build(S.li_pts(s, d).withColumn("id", F.xxhash64("id"))).points.groupBy("block").count().agg(F.sum("count").alias("n")), f"with {RP} select cast(count(*) as bigint) as n from rp")
add("rect_sum", lambda s, d: rect(s, d).agg_many(one(s)).select("a"), f"with {RP} select cast(sum(w) as bigint) as a from rp where {ONE}")
add("rect_count", lambda s, d: rect(s, d).count_many(one(s)).select("a"), f"with {RP} select count(*) as a from rp where {ONE}")
add("rect_sum_many", lambda s, d: rect(s, d).agg_many(S.q_rect(s, d)), RSUM)
add("rect_sum_dominance", lambda s, d: rect(s, d).sums_many(S.q_rect(s, d)).select("qid", "a"), RSUM)
add("rect_sum_cover", lambda s, d: rect(s, d).cover_many(S.q_rect(s, d), M.sum_()), RSUM)
add("rect_max_many", lambda s, d: rect(s, d).agg_many(S.q_rect(s, d), M.max_()), f"with {RP}, {RQ} select qid, max(w) as a from rq left join rp on x between xl and xr and y between yl and yr group by 1")
RLIST = f"with {RP}, {RQ} select qid, count(*) as n from rq join rp on x between xl and xr and y between yl and yr where qid % 50 = 0 group by 1"
add("rect_list", lambda s, d: rect(s, d).list_many(one(s)).agg(F.count("*").alias("n")), f"with {RP} select count(*) as n from rp where {ONE}")
add("rect_list_many", lambda s, d: rect(s, d).list_many(S.searched(S.q_rect(s, d))).groupBy("qid").agg(F.count("*").alias("n")), RLIST)
add("rect_level_counts", lambda s, d: _levels(s, d), f"with {RP} select 0::bigint as wrong, count(*) as n, cast(sum(w) as bigint) as a from rp")
add("msr_level_rows", Q["rect_level_counts"][0], Q["rect_level_counts"][1])
add("msr_output_sizes", lambda s, d: rect(s, d).count_many(S.searched(S.q_rect(s, d))).filter("a > 0").select("qid", F.col("a").alias("n")), RLIST)
add("wl_rect_sum", Q["rect_sum_many"][0], RSUM)
add("wl_rect_list", Q["rect_list_many"][0], RLIST)
add("base_rect_scan", lambda s, d: B.rect_sums_scan(S.li_pts(s, d), S.q_rect(s, d)), f"with {RP}, {RQ} select qid, cast(sum(w) as bigint) as a from rq join rp on x between xl and xr and y between yl and yr group by 1")
BX = "bx as (select o_orderkey as id, epoch_us(least(o_orderdate, s)) as lo, epoch_us(greatest(o_orderdate, s)) as hi, cast(round(o_totalprice*100) as bigint) as y from orders join (select l_orderkey, max(l_shipdate) as s from lineitem group by 1) on o_orderkey = l_orderkey)"
add("rect_overlap", lambda s, d: _rect_overlap(s, d), f"with {BX} select a.id as aid, b.id as bid from bx a join bx b on a.lo <= b.hi and b.lo <= a.hi and abs(a.y - b.y) <= 10000 where a.id % 50 = 0")
add("seg_cross", lambda s, d: I.segments_crossing(_bars(s, d), _bars(s, d).filter("id % 50 = 0").select("id", F.expr("(lo + hi) div 2 as x"), (F.col("y") - 100000).alias("ylo"), (F.col("y") + 100000).alias("yhi"))), f"with {BX} select h.id as hid, v.id as vid from bx h join bx v on h.lo < (v.lo + v.hi) // 2 and (v.lo + v.hi) // 2 < h.hi and h.y between v.y - 100000 and v.y + 100000 where v.id % 50 = 0")
add("pt_locate", lambda s, d: I.locate(_bars(s, d), _bars(s, d).filter("id % 50 = 0").select(F.col("id").alias("pid"), F.expr("(lo + hi) div 2 as x"), (F.col("y") - 1).alias("y"))), f"with {BX} select v.id as pid, arg_max(h.id, (h.y, h.id)) as hid from bx h join bx v on h.lo < (v.lo + v.hi) // 2 and (v.lo + v.hi) // 2 < h.hi and h.y <= v.y - 1 where v.id % 50 = 0 group by 1")
add("box3_sum", lambda s, d: _box3(s, d), f"with {RP}, {RQ} select qid, cast(coalesce(sum(w), 0) as bigint) as a from rq left join rp on x between xl and xr and y between yl and yr and w between 10 and 30 group by 1")


def _bars(s, d):
    """Orders' intervals at the height of their price, written once a session for the passes over them; a small table too
    lies in files enough for every core."""
    return scratch.kept(s, ("order-bars", d), lambda: S.ord_bars(s, d).repartition(4 * s.sparkContext.defaultParallelism, "id"))


def _rect_overlap(s, d):
    h = _bars(s, d)
    a = h.filter("id % 50 = 0").select("id", "lo", "hi", (F.col("y") - 10000).alias("ylo"), (F.col("y") + 10000).alias("yhi"))
    return I.overlap_pairs(a, h)


def _box3(s, d):
    """Third axis: the weight itself. The inner index is kept for the points of its band of the third axis."""
    r = rect(s, d)
    return replace(r, points=r.points.filter("w between 10 and 30"), nested=r.nested.filter("w between 10 and 30")).agg_many(S.q_rect(s, d))


def _levels(s, d):
    """Levels of the stored index that don't hold every point once, with its weight: none. And what one holds."""
    r = rect(s, d)
    per = r.nested.groupBy("level").agg(F.sum("n").alias("n"), F.sum(F.col("w") * F.col("n")).alias("a"))
    one = r.points.agg(F.count("*").alias("pn"), F.sum("w").alias("pa"))
    return per.crossJoin(one).agg(F.count(F.when((F.col("n") != F.col("pn")) | (F.col("a") != F.col("pa")), 1)).alias("wrong"), F.max("pn").alias("n"), F.max("pa").alias("a"))


# ---- ranked index
add("idx_tokens", lambda s, d: X.tokenize(S.table(s, d, "documents"), "doc_id", "text").groupBy("term").agg(F.count("*").alias("n")), f"with {TOK} select term, count(*) as n from tok where term <> '' group by 1")
add("idx_tokens_html", lambda s, d: X.tokenize(S.table(s, d, "pages"), "page_id", "html", "ascii", True).groupBy("term").agg(F.count("*").alias("n")), "select term, count(*) as n from (select unnest(string_split_regex(lower(regexp_replace(html, '<[^>]*>', ' ', 'g')), '[^a-z0-9]+')) as term from pages) where term <> '' group by 1")
add("idx_weights", lambda s, d: X.weigh(X.tokenize(S.table(s, d, "documents"), "doc_id", "text")), f"with {IDX} select term, doc_id, tf, w from idx")
add("idx_weights_quality", lambda s, d: X.weigh(X.tokenize(S.table(s, d, "documents"), "doc_id", "text"), "tf_quality", S.table(s, d, "labels")), f"with {IDX} select term, doc_id, tf, tf * (1 + coalesce(quality, 0)) as w from idx left join labels using (doc_id)")
BUILD = f"with {IDX} select term, count(*) as df, cast(sum(w) as bigint) as sum_w, max(w) as max_w from idx group by 1"
add("idx_build", lambda s, d: built_index(s, d).terms(), BUILD)
add("idx_posting", lambda s, d: index(s, d).postings.filter("term = 'the'"), f"with {IDX} select term, doc_id, w from idx where term = 'the'")
AND = f"with {IDX} select doc_id, cast(sum(w) as bigint) as w from idx where term in ('the', 'of') group by 1 having count(*) = 2"
OR = f"with {IDX} select doc_id, cast(sum(w) as bigint) as w from idx where term in ('the', 'und') group by 1"
add("idx_and", lambda s, d: index(s, d).search_and(["the", "of"]), AND)
add("idx_or", lambda s, d: index(s, d).search_or(["the", "und"]), OR)
add("idx_and_not", lambda s, d: index(s, d).search_and_not("the", "und"), f"with {IDX} select doc_id, w from idx where term = 'the' and doc_id not in (select doc_id from idx where term = 'und')")
TOP = "select row_number() over (order by w desc, doc_id) as rk, doc_id, w from ({}) order by rk limit 10"
add("idx_and_top10", lambda s, d: X.top_k(index(s, d).top_k(["the", "of"])), f"with {IDX} " + TOP.format(AND.split(" ", 1)[1].removeprefix(IDX).strip()))
add("idx_or_top10", lambda s, d: X.top_k(index(s, d).top_k(["the", "und"], "or")), f"with {IDX} " + TOP.format(OR.split(" ", 1)[1].removeprefix(IDX).strip()))
BATCH = f"with {IDX}, {QA}, dq as (select distinct t1, t2 from qa), r as (select t1, t2, a.doc_id, a.w + b.w as w, row_number() over (partition by t1, t2 order by a.w + b.w desc, a.doc_id) as rk from dq join idx a on a.term = t1 join idx b on b.term = t2 and a.doc_id = b.doc_id) select qid, cast(rk as int) as rk, doc_id, w from qa join r using (t1, t2) where rk <= 10"
add("idx_batch_top10", lambda s, d: index(s, d).search_batch(asked(s, d)), BATCH)
add("wl_index_build", Q["idx_build"][0], BUILD)
add("wl_and_top10", Q["idx_batch_top10"][0], BATCH)
add("msr_postings_touched", lambda s, d: X.postings_touched(index(s, d), asked(s, d)), f"with {IDX}, {QA}, df as (select term, count(*) as n from idx group by 1) select cast(sum(a.n + b.n) as bigint) as touched from qa join df a on a.term = t1 join df b on b.term = t2")
add("base_idx_fullsort", lambda s, d: _fullsort(s, d), BATCH)


def _fullsort(s, d):
    """Equal queries are answered once here too; every match is ranked, then cut."""
    q = asked(s, d).select("qid", F.array_sort("terms").alias("terms"))
    found = index(s, d).matches(q)
    if found is not None:
        known, hits = found
        best = B.topk_fullsort(hits.withColumnRenamed("sid", "qid"), 10).withColumnRenamed("qid", "sid")
        return q.join(known, "terms").join(best, "sid").select("qid", "rk", "doc_id", "w")
    one = q.groupBy("terms").agg(F.min("qid").alias("one"))
    hits = one.select(F.col("one").alias("qid"), F.explode("terms").alias("term")).join(index(s, d).postings, "term")
    hits = hits.groupBy("qid", "doc_id").agg(F.sum("w").alias("w"), F.count("*").alias("m")).filter("m = 2").select("qid", "doc_id", "w")
    best = B.topk_fullsort(hits, 10).withColumnRenamed("qid", "one")
    return q.join(one, "terms").join(best, "one").select("qid", "rk", "doc_id", "w")


# ---- store and streams
def _scratch(s, name):
    return scratch.place(s, name)


def _store(s, d):
    from ordsum.sources.store import VersionStore

    st = VersionStore(s, _scratch(s, "store"), Layout(block_rows=1024))
    m = SummaryMap.build(S.orders(s, d), "k", "v", M.sum_(), layout=st.layout)
    st.commit(m)
    return st


def _store_insert(s, d):
    st = _store(s, d)
    v = st.insert_many(S.orders(s, d).filter("k between 100 and 114").select("k", F.lit(1).cast("bigint").alias("v")), lambda old, new: old + new)
    return st.snapshot(v).entries()


def _ingest(s, d):
    from ordsum.sources.store import VersionStore
    from ordsum.streaming.ingest import ingest

    st = VersionStore(s, _scratch(s, "stream"), Layout(block_rows=1024))
    old = S.ev_map(s, d).filter("event_id % 2 = 0").select("k", "v")
    st.commit(SummaryMap.build(old, "k", "v", h="all", layout=st.layout))
    src = s.read.parquet(f"{d}/events.parquet")
    stream = s.readStream.schema(src.schema).parquet(f"{d}/events.parquet*").filter("event_id % 2 = 1").select(S.micros("ts").alias("k"), S.cents("value").alias("v"))
    ingest(stream, st, _scratch(s, "progress")).awaitTermination()
    return st.snapshot().entries()


add("src_map_store", lambda s, d: _store(s, d).snapshot().entries(), "select o_orderkey as k, cast(round(o_totalprice*100) as bigint) as v from orders")
add("src_store_insert", _store_insert, "select o_orderkey as k, cast(round(o_totalprice*100) as bigint) + case when o_orderkey between 100 and 114 then 1 else 0 end as v from orders")
add("st_ingest", _ingest, "select epoch_us(ts) as k, cast(round(value*100) as bigint) as v from events")
