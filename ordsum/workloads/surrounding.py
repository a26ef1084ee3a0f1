"""What a user needs around the map: joins, aggregates, windows, sets, functions, windows of time, UDFs.

Most are SQL text that runs in both engines; where the dialects differ there are two texts,
and operators without SQL in Spark are written with the DataFrame API."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ordsum.functions import monoids as M
from ordsum.operators import batch as R
from ordsum.operators.maps import Layout, SummaryMap
from ordsum.sources import tables as S

TABLES = "region nation customer supplier part orders lineitem events documents pages benchmark labels conversations".split()
C = "cast(round({0}*100) as bigint)"

Q: dict = {}


def add(name: str, f, sql: str | None) -> None:
    Q[name] = (f, sql)


def text(name: str, spark_sql: str, other: str | None = None) -> None:
    """Runs SQL over views of the tables named in it."""

    def run(spark, d) -> DataFrame:
        for t in TABLES:
            if t in spark_sql:
                S.table(spark, d, t).createOrReplaceTempView(t)
        return spark.sql(spark_sql)

    add(name, run, other or spark_sql)


def us(c: str) -> str:
    return f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', {c})"


def pair(name: str, sql: str) -> None:
    """SQL with {us:col} for microseconds since the epoch, which the two dialects spell differently."""
    import re

    text(name, re.sub(r"\{us:(\w+)\}", lambda m: us(m[1]), sql), re.sub(r"\{us:(\w+)\}", r"epoch_us(\1)", sql))


text("src_parquet_count", " union all ".join(f"select '{t}' as t, count(*) as n from {t}" for t in TABLES))


def _roundtrip(kind: str):
    def run(spark, d):
        from ordsum.workloads.apps import _scratch

        src = S.table(spark, d, "nation")
        path = _scratch(spark, kind)
        getattr(src.write, kind)(path)
        return getattr(spark.read.schema(src.schema), kind)(path)

    return run


add("src_csv_roundtrip", _roundtrip("csv"), "select * from nation")
add("src_json_roundtrip", _roundtrip("json"), "select * from nation")
pair("gen_project_filter", f"select l_orderkey, l_linenumber, {C.format('l_extendedprice')} as cents from lineitem where {{us:l_shipdate}} >= 852076800000000 and {{us:l_shipdate}} < 883612800000000")
text("gen_json_filter", "select event_id from events where cast(get_json_object(props, '$.k') as int) >= 50", "select event_id from events where cast(props->>'k' as int) >= 50")
text("gen_case_null", "select c_custkey, case when c_acctbal < 0 then 'debt' when c_acctbal < 5000 then 'low' else 'high' end as class, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') as seg, c_nationkey is not distinct from 3 as three from customer")
text("gen_in_like", "select p_partkey from part where p_size in (1, 5, 9) and (p_type like 'S%' or p_brand like '%1')")
text("join_inner", "select o_orderkey, c_name from orders join customer on o_custkey = c_custkey")
text("join_broadcast", f"select /*+ broadcast(supplier), broadcast(nation), broadcast(region) */ r_name, sum({C.format('l_extendedprice')}) as cents from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by r_name", f"select r_name, cast(sum({C.format('l_extendedprice')}) as bigint) as cents from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by r_name")
text("join_sortmerge", "select /*+ merge(orders) */ o_orderkey, count(*) as n from orders join lineitem on o_orderkey = l_orderkey group by o_orderkey", "select o_orderkey, count(*) as n from orders join lineitem on o_orderkey = l_orderkey group by o_orderkey")
text("join_left", "select o_orderkey, l_linenumber from orders left join lineitem on o_orderkey = l_orderkey")
text("join_full", "select c_custkey, s_suppkey from (select * from customer where c_custkey < 100) c full outer join (select * from supplier where s_suppkey < 50) s on c_nationkey = s_nationkey")
text("join_semi", "select c_custkey from customer where c_custkey in (select o_custkey from orders)")
text("join_anti", "select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey)")
text("join_theta", "select a.r_regionkey as a, b.r_regionkey as b from region a join region b on a.r_regionkey < b.r_regionkey")
text("join_cross", "select r_name, event_type from region cross join (select distinct event_type from events)")
pair("join_self", "with e as (select event_id, user_id, row_number() over (partition by user_id order by {us:ts}) as r from events) select a.event_id as a, b.event_id as b from e a join e b on a.user_id = b.user_id and b.r = a.r + 1")
add("join_range", lambda s, d: R.range_many(SummaryMap.build(S.li_ship(s, d), "k", "v", M.sum_(), h="sum", layout=Layout(block_rows=64)), S.q_90d(s, d)).groupBy("qid").agg(F.count("*").alias("n"), F.sum("v").alias("v")),
    "with w as (select o_orderkey as qid, epoch_us(o_orderdate) as lo from orders), ls as (select epoch_us(l_shipdate) as k, cast(sum(cast(round(l_extendedprice*100) as bigint)) as bigint) as v from lineitem group by 1) select qid, count(*) as n, cast(sum(v) as bigint) as v from w join ls on k between lo and lo + 7776000000000 group by 1")


def asof(forward: bool, within: int | None):
    """Each purchase with the last view before it (or the next one after) of the same user, in one window."""

    def run(spark, d):
        e = S.table(spark, d, "events").select("event_id", "user_id", "event_type", S.micros("ts").alias("t")).filter("event_type in ('purchase', 'view')")
        order = W.partitionBy("user_id").orderBy("t")
        seen = F.when(F.col("event_type") == "view", F.struct("t", "event_id"))
        near = F.first(seen, True).over(order.rowsBetween(0, W.unboundedFollowing)) if forward else F.last(seen, True).over(order.rowsBetween(W.unboundedPreceding, 0))
        got = e.withColumn("m", near).filter("event_type = 'purchase'")
        ok = F.lit(True) if within is None else F.abs(F.col("t") - F.col("m.t")) <= within
        return got.select("event_id", F.when(ok, F.col("m.event_id")).alias("view_id"))

    return run


def asof_sql(forward: bool, within: int | None) -> str:
    side, agg = (">=", "arg_min") if forward else ("<=", "arg_max")
    near = f" and abs(epoch_us(v.ts) - epoch_us(p.ts)) <= {within}" if within else ""
    return f"select p.event_id, {agg}(v.event_id, v.ts) as view_id from (select * from events where event_type = 'purchase') p left join (select * from events where event_type = 'view') v on p.user_id = v.user_id and v.ts {side} p.ts{near} group by 1"


for _n, _f, _w in (("backward", False, None), ("forward", True, None), ("tolerance", False, 3_600_000_000)):
    add(f"join_asof_{_n}", asof(_f, _w), asof_sql(_f, _w))


def _join_interval(s, d):
    """The ten days after each order whose key is divisible by fifty, held against all orders' intervals."""
    from ordsum.operators.intervals import overlap_totals

    # orders of one moment ask the same
    o = S.searched(S.table(s, d, "orders").select(F.col("o_orderkey").alias("qid"), S.micros("o_orderdate").alias("lo")))
    met = lambda q: overlap_totals(q.select(F.col("qid").alias("id"), "lo", (F.col("lo") + 10 * S.DAY).alias("hi")), S.ord_iv(s, d))
    return R.once(o, ["lo"], lambda q: met(q).select(F.col("aid").alias("qid"), "n", F.col("total").alias("bids")), ["n", "bids"]).withColumnRenamed("qid", "aid")


add("join_interval", _join_interval, "with iv as (select o_orderkey as id, epoch_us(least(o_orderdate, s)) as lo, epoch_us(greatest(o_orderdate, s)) as hi from orders join (select l_orderkey, max(l_shipdate) as s from lineitem group by 1) on o_orderkey = l_orderkey), w as (select o_orderkey as id, epoch_us(o_orderdate) as lo, epoch_us(o_orderdate) + 864000000000 as hi from orders where o_orderkey % 50 = 0) select w.id as aid, count(*) as n, cast(sum(iv.id) as bigint) as bids from w join iv on w.lo <= iv.hi and iv.lo <= w.hi group by 1")

text("agg_group", f"select l_returnflag, l_linestatus, cast(sum({C.format('l_extendedprice')}) as bigint) as cents, count(*) as n, round(sum({C.format('l_extendedprice')}) / count(*), 2) as mean from lineitem group by l_returnflag, l_linestatus")
pair("agg_distinct", "select {us:o_orderdate} % 7 as m, count(distinct o_custkey) as n from orders group by 1")
text("agg_filter_clause", "select event_type, count(*) filter (where value > 50) as big, count(case when value <= 50 then 1 end) as small from events group by event_type")
for _n, _g in (("rollup", "rollup (o_orderstatus, o_orderpriority)"), ("cube", "cube (o_orderstatus, o_orderpriority)"), ("grouping_sets", "grouping sets ((o_orderstatus), (o_orderpriority), ())")):
    text(f"agg_{_n}", f"select o_orderstatus, o_orderpriority, cast(grouping(o_orderstatus) as int) as g, count(*) as n from orders group by {_g}")
add("agg_pivot", lambda s, d: S.table(s, d, "events").groupBy((F.col("user_id") % 10).alias("u")).pivot("event_type", ["click", "purchase", "view"]).count().na.fill(0, ["click", "purchase", "view"]),
    "select user_id % 10 as u, count(*) filter (where event_type = 'click') as click, count(*) filter (where event_type = 'purchase') as purchase, count(*) filter (where event_type = 'view') as \"view\" from events group by 1")
text("agg_min_by", f"select o_custkey, max_by(o_orderkey, struct({C.format('o_totalprice')}, o_orderkey)) as best from orders group by o_custkey", f"select o_custkey, arg_max(o_orderkey, ({C.format('o_totalprice')}, o_orderkey)) as best from orders group by o_custkey")
text("agg_collect", "select l_orderkey, array_join(array_sort(collect_list(cast(l_linenumber as int))), ',') as l from lineitem group by l_orderkey", "select l_orderkey, string_agg(l_linenumber::varchar, ',' order by l_linenumber) as l from lineitem group by l_orderkey")
text("agg_percentile", f"select event_type, cast(percentile_disc(0.5) within group (order by {C.format('value')}) as bigint) as p50 from events group by event_type")
add("agg_approx_distinct", lambda s, d: S.table(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("n")), None)
text("agg_bool", "select user_id, bool_or(event_type = 'error') as any_error, bool_and(value > 1) as all_big from events group by user_id")
text("agg_bits", "select user_id, bit_xor(event_id) as x, bit_or(event_id) as o from events group by user_id")

pair("win_rank", f"select o_orderkey, row_number() over (partition by o_custkey order by {{us:o_orderdate}}, o_orderkey) as rn, rank() over (partition by o_custkey order by o_orderpriority) as rk, dense_rank() over (partition by o_custkey order by o_orderpriority) as dr, ntile(3) over (partition by o_custkey order by o_orderkey) as nt from orders")
pair("win_lag", "select event_id, {us:ts} - lag({us:ts}) over (partition by user_id order by ts) as gap, lead(event_id) over (partition by user_id order by ts) as nxt from events")
text("win_running_sum", f"select event_id, cast(sum({C.format('value')}) over (partition by user_id order by ts rows between unbounded preceding and current row) as bigint) as s from events")
pair("win_range_frame", f"select event_id, cast(sum(v) over (partition by user_id order by t range between 86400000000 preceding and current row) as bigint) as s from (select event_id, user_id, {{us:ts}} as t, {C.format('value')} as v from events)")
text("win_sliding_max", f"select event_id, max({C.format('value')}) over (partition by user_id order by ts rows between 9 preceding and current row) as m from events")
text("win_first_last_nth", "select event_id, first_value(event_id) over w as f, last_value(event_id) over w as l, nth_value(event_id, 2) over w as n from events window w as (partition by user_id order by ts rows between unbounded preceding and unbounded following)")
text("win_percent_rank", f"select p_partkey, round(percent_rank() over (partition by p_brand order by p_retailprice), 6) as pr, round(cume_dist() over (partition by p_brand order by p_retailprice), 6) as cd from part")
text("sort_topk", "select o_orderkey from orders order by o_totalprice desc, o_orderkey limit 25")
text("sort_topk_group", "select o_custkey, o_orderkey from (select *, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as r from orders) where r <= 2")
text("sort_limit_offset", "select o_orderkey from orders order by o_totalprice desc, o_orderkey limit 25 offset 25")
text("set_union", "select o_custkey as k from orders union select c_custkey from customer where c_custkey < 50")
text("set_union_all", "select l_partkey as k from lineitem where l_orderkey < 100 union all select p_partkey from part where p_partkey < 50")
text("set_intersect", "select c_custkey as k from customer intersect select o_custkey from orders")
text("set_except", "select c_custkey as k from customer except select o_custkey from orders")
text("set_except_all", "select l_partkey as k from lineitem where l_orderkey < 300 except all select p_partkey from part where p_partkey < 500")
text("fn_string", "select c_custkey, lower(c_name) as a, upper(c_mktsegment) as b, trim(concat(' ', c_name, ' ')) as c, substr(c_name, 3, 4) as e, replace(c_name, '0', 'x') as f, length(c_name) as g, md5(c_name) as h, reverse(c_name) as i, lpad(c_name, 30, '*') as j from customer")
pair("fn_date", "select o_orderkey, year(o_orderdate) as y, month(o_orderdate) as m, day(o_orderdate) as dd, {us:o_orderdate} as us, quarter(o_orderdate) as qu from orders")
text("fn_math", "select l_orderkey, l_linenumber, abs(l_orderkey - 50) as a, floor(l_orderkey / 7.0) as f, ceil(l_orderkey / 7.0) as c, ((l_orderkey - 9) % 5 + 5) % 5 as p, l_orderkey & 12 as b, sign(l_orderkey - 50) as s from lineitem", "select l_orderkey, l_linenumber, abs(l_orderkey - 50) as a, cast(floor(l_orderkey / 7.0) as bigint) as f, cast(ceil(l_orderkey / 7.0) as bigint) as c, ((l_orderkey - 9) % 5 + 5) % 5 as p, l_orderkey & 12 as b, cast(sign(l_orderkey - 50) as double) as s from lineitem")
text("fn_array", "select doc_id, size(t) as n, size(array_distinct(t)) as u, aggregate(transform(t, x -> length(x)), 0, (a, b) -> a + b) as l from (select doc_id, filter(split(text, ' '), x -> x <> '') as t from documents)", "select doc_id, len(t) as n, len(list_distinct(t)) as u, cast(list_sum(list_transform(t, lambda x: length(x))) as bigint) as l from (select doc_id, list_filter(string_split(text, ' '), lambda x: x <> '') as t from documents)")
text("fn_map", "select u, coalesce(element_at(map_from_entries(collect_list(struct(event_type, n))), 'view'), 0) as views from (select user_id as u, event_type, count(*) as n from events group by 1, 2) group by u", "select user_id as u, count(*) filter (where event_type = 'view') as views from events group by 1")
text("fn_json", "select event_id, from_json(props, 'k int').k as k, to_json(named_struct('e', event_id)) as j from events", "select event_id, cast(props->>'k' as int) as k, '{\"e\":' || event_id || '}' as j from events")
text("fn_struct", "select l_orderkey, l_linenumber from lineitem where struct(l_orderkey, l_linenumber) < struct(50L, 3)", "select l_orderkey, l_linenumber from lineitem where (l_orderkey, l_linenumber) < (50, 3)")
HOUR, QUARTER, DAYS = 3_600_000_000, 900_000_000, 86_400_000_000
add("st_tumbling", lambda s, d: S.table(s, d, "events").groupBy(F.window("ts", "1 hour").alias("w")).count().select(S.micros("w.start").alias("t"), F.col("count").alias("n")), f"select epoch_us(ts) // {HOUR} * {HOUR} as t, count(*) as n from events group by 1")
add("st_sliding", lambda s, d: S.table(s, d, "events").groupBy(F.window("ts", "1 hour", "15 minutes").alias("w")).count().select(S.micros("w.start").alias("t"), F.col("count").alias("n")), f"select epoch_us(ts) // {QUARTER} * {QUARTER} - o * {QUARTER} as t, count(*) as n from events cross join range(4) r(o) group by 1")
add("st_session", lambda s, d: S.sess_iv(s, d), "with e as (select user_id, epoch_us(ts) as t from events), f as (select *, case when t - lag(t) over (partition by user_id order by t) <= 21600000000 then 0 else 1 end as nw from e), g as (select *, sum(nw) over (partition by user_id order by t) as sid from f) select cast(user_id * 1000000 + sid as bigint) as id, min(t) as lo, max(t) as hi from g group by user_id, sid")
add("st_dedup", lambda s, d: S.table(s, d, "events").select("user_id", "event_type", F.floor(S.micros("ts") / HOUR).alias("h")).dropDuplicates(), f"select distinct user_id, event_type, epoch_us(ts) // {HOUR} as h from events")


def _stream(s, d, sink):
    """Runs a query on `events` read as a stream and gives what it wrote: files where rows are only added, otherwise a
    memory table of its own."""
    import uuid

    from ordsum.workloads.apps import _scratch

    schema = S.table(s, d, "events").schema
    src = s.readStream.schema(schema).parquet(f"{d}/events.parquet*")
    name = f"t{uuid.uuid4().hex}"
    out, mode = sink(src)
    if mode == "append":
        path = _scratch(s, "stream-out")
        out.writeStream.format("parquet").outputMode(mode).option("checkpointLocation", _scratch(s, "progress")).trigger(availableNow=True).start(path).awaitTermination()
        return s.read.schema(out.schema).parquet(path)
    out.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", _scratch(s, "progress")).trigger(availableNow=True).start().awaitTermination()
    return s.table(name)


def _late(s, d):
    """Events come in two files, the later half of the time first. Once its watermark (a day before the last event) has
    passed, the hours of the earlier half are closed: all its rows but those of the last day come too late."""
    import uuid

    from ordsum.sources import scratch
    from ordsum.streaming.ingest import late_filtered

    e = S.table(s, d, "events").select(F.col("ts").cast("timestamp").alias("ts"), "event_id")
    folder = scratch.place(s, "late")
    cut = "timestamp'2024-01-16'"
    for n, part in enumerate((f"ts >= {cut}", f"ts < {cut}", "ts is null")):
        e.filter(part).coalesce(1).write.parquet(f"{folder}/{n}")
    end = s.createDataFrame([("2030-01-01", -1)], "ts string, event_id bigint").select(F.col("ts").cast("timestamp").alias("ts"), "event_id")
    out, name, progress = None, f"t{uuid.uuid4().hex}", scratch.place(s, "progress")
    read = scratch.place(s, "late-read")
    for n in range(3):  # one file arrives, is read, and then the next
        src = s.read.parquet(f"{folder}/{n}") if n < 2 else end
        src.coalesce(1).write.mode("append").parquet(read)
        stream = s.readStream.schema(e.schema).parquet(read)
        out = late_filtered(stream, "ts", "1 day", "1 hour").select(F.col("window.start").alias("start"), "count")
        out.writeStream.format("parquet").option("path", f"{folder}/out-{name}").outputMode("append").option("checkpointLocation", progress).trigger(availableNow=True).start().awaitTermination()
    return s.read.parquet(f"{folder}/out-{name}").select(F.expr("unix_micros(start)").alias("t"), F.col("count").alias("n"))


add("st_watermark_late", _late, "with e as (select epoch_us(ts) as t, ts from events), w as (select max(t) - 86400000000 as m from e) select t // 3600000000 * 3600000000 as t, count(*) as n from e, w where ts >= timestamp '2024-01-16' or t // 3600000000 * 3600000000 + 3600000000 > m group by 1")
add("st_stream_static", lambda s, d: _stream(s, d, lambda src: (src.select("event_id", "user_id").join(S.table(s, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_name"), "user_id").select("event_id", "c_name"), "append")), "select event_id, c_name from events join customer on user_id = c_custkey")


def _running(s, d):
    from ordsum.streaming.ingest import running_sums

    return _stream(s, d, lambda src: (running_sums(src.select("user_id", S.cents("value").alias("v"))), "update"))


add("st_stateful_prefix", _running, "select user_id, count(*) as n, cast(sum(cast(round(value*100) as bigint)) as bigint) as total from events group by 1")


def _udf_base(s, d):
    @F.pandas_udf("bigint")
    def weight(v: pd.Series) -> pd.Series:
        return v % 97 + 1

    return S.ev_map(s, d).select("k", weight("v").alias("v"))


def _udaf(s, d):
    @F.pandas_udf("bigint")
    def spread(v: pd.Series) -> int:
        return int(v.max() - v.min())

    return S.ev_map(s, d).groupBy("user_id").agg(spread("v").alias("spread"))


def _udaf_ordered(s, d):
    """Affine maps composed in key order, block by block, then across blocks."""
    m = SummaryMap.build(S.ev_map(s, d), "k", "v", M.affine(), lambda k, v: F.struct((v % 5 + 1).alias("p"), (v % 11).alias("q")), h="all", layout=Layout(block_rows=512, fanout=4))
    return m.summary().select("a.p", "a.q")


def _udtf(s, d):
    from pyspark.sql.functions import udtf

    @udtf(returnType="level int, node bigint")
    class Cover:
        """Pyramid nodes of fan-out 4 whose blocks are exactly a..b."""

        def eval(self, a: int, b: int):
            level = 0
            while a <= b:
                while a <= b and (a % 4 or a + 3 > b):
                    yield level, a
                    a += 1
                tail = []
                while a <= b and (b + 1) % 4:
                    tail.append(b)
                    b -= 1
                for n in reversed(tail):
                    yield level, n
                a, b, level = a // 4, (b + 1) // 4 - 1, level + 1

    s.udtf.register("cover_nodes", Cover)
    S.table(s, d, "orders").selectExpr("o_orderkey as qid", "o_orderkey % 50 as a", "o_orderkey % 50 + o_custkey % 200 as b").createOrReplaceTempView("spans_to_cover")
    return s.sql("select qid, sum(cast(power(4, level) as bigint)) as blocks from spans_to_cover, lateral cover_nodes(a, b) group by qid")


def _sql_range(s, d):
    m = SummaryMap.build(S.ev_map(s, d), "k", "v", M.sum_(), h="all", layout=Layout(block_rows=512))
    m.rows.createOrReplaceTempView("map_rows")
    m.block_table().createOrReplaceTempView("map_blocks")
    lo, hi = 1_704_844_800_000_000, 1_705_708_800_000_000
    return s.sql(f"with b as (select * from map_blocks), inside as (select sum(a) as a from b where lo >= {lo} and hi <= {hi}), edge as (select sum(v) as a from map_rows join b using (block) where not (b.lo >= {lo} and b.hi <= {hi}) and k between {lo} and {hi}) select coalesce(inside.a, 0) + coalesce(edge.a, 0) as a from inside cross join edge")


EV = "ev as (select epoch_us(ts) as k, cast(round(value*100) as bigint) as v, event_id, user_id from events)"
add("udf_base", _udf_base, f"with {EV} select k, v % 97 + 1 as v from ev")
add("udaf_combine", _udaf, f"with {EV} select user_id, max(v) - min(v) as spread from ev group by 1")
add("udaf_ordered", _udaf_ordered, f"with recursive {EV}, e as (select row_number() over (order by k) as r, v % 5 + 1 as p, v % 11 as q from ev), f as (select 0::bigint as r, 1::bigint as p, 0::bigint as q union all select e.r, (f.p * e.p) % 1000003, (e.p * f.q + e.q) % 1000003 from f join e on e.r = f.r + 1) select p, q from f order by r desc limit 1")
add("udtf_cover", _udtf, "select o_orderkey as qid, o_custkey % 200 + 1 as blocks from orders")
add("sql_summary_range", _sql_range, f"with {EV} select cast(sum(v) as bigint) as a from ev where k between 1704844800000000 and 1705708800000000")
