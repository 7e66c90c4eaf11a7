"""Relational operators around the methods, each as a query on the given tables with its DuckDB twin."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import columns, register
from ..sources import scratch
from ..sources.objects import movements, objects, pick
from ..sources.tables import load, read_any, write_any

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def _op(sql: str | None):
    """Register a query under its function's name, with its twin."""

    def take(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return take


def _year(column: str):
    return F.year(column).cast("long")


@_op("select l_partkey, l_shipdate, l_quantity from lineitem where l_shipdate >= timestamp '1998-01-01'")
def op_scan_pruned(spark, d):
    return load(spark, d, "lineitem", "l_partkey", "l_shipdate", "l_quantity").where("l_shipdate >= timestamp_ntz '1998-01-01'")


@_op("select event_id from events where value between 100 and 300 and event_type in (select event_type from (select distinct event_type from events) order by event_type limit 2) and props is not null")
def op_filter_bool_null(spark, d):
    e = load(spark, d, "events", "event_id", "event_type", "value", "props")
    two = e.select("event_type").distinct().orderBy("event_type").limit(2)
    return e.where(F.col("value").between(100, 300) & F.col("props").isNotNull()).join(F.broadcast(two), "event_type", "left_semi").select("event_id")


@_op("select o_orderkey, case when o_totalprice < 100000 then 'low' when o_totalprice < 300000 then 'mid' else 'high' end as band from orders")
def op_project_case(spark, d):
    p = F.col("o_totalprice")
    return load(spark, d, "orders", "o_orderkey", "o_totalprice").select("o_orderkey", F.when(p < 100000, "low").when(p < 300000, "mid").otherwise("high").alias("band"))


def _roundtrip(form: str, whole: bool = False):
    def run(spark, d):
        path = scratch.new_path(spark, f"roundtrip-{form}")
        df = load(spark, d, "orders", "o_orderkey", "o_custkey", "o_totalprice", "o_orderpriority")
        df = df if whole else df.where("o_orderkey <= 1000")
        write_any(df, path, form)
        return read_any(spark, path, form, df.schema)

    run.__name__ = f"op_roundtrip_{form}{'_whole' if whole else ''}"
    return run


for _form in ("parquet", "csv", "json", "orc"):
    _op("select o_orderkey, o_custkey, o_totalprice, o_orderpriority from orders where o_orderkey <= 1000")(_roundtrip(_form))
    _op("select o_orderkey, o_custkey, o_totalprice, o_orderpriority from orders")(_roundtrip(_form, True))


@_op("select n_nationkey, case when n_regionkey = 1 then upper(n_name) else n_name end as name, n_regionkey from nation")
def op_partitioned_overwrite(spark, d):
    path = scratch.new_path(spark, "parts")
    n = load(spark, d, "nation").selectExpr("cast(n_nationkey as long) n_nationkey", "n_name as name", "cast(n_regionkey as long) n_regionkey")
    write_any(n, path, "parquet", by=["n_regionkey"])
    write_any(n.where("n_regionkey = 1").withColumn("name", F.upper("name")), path, "parquet", mode="parts", by=["n_regionkey"])
    return read_any(spark, path, "parquet", n.select("n_nationkey", "name", "n_regionkey").schema)


@_op("select doc_id, line from (select doc_id, unnest(string_split(text, chr(10))) as line from documents) where trim(line) <> ''")
def op_text_lines(spark, d):
    return load(spark, d, "documents", "doc_id", "text").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where(F.trim("line") != "")


@_op("select c_custkey, n_name, r_name from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey")
def op_join_broadcast(spark, d):
    n, r = load(spark, d, "nation", "n_nationkey", "n_name", "n_regionkey"), load(spark, d, "region", "r_regionkey", "r_name")
    small = n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey)
    return load(spark, d, "customer", "c_custkey", "c_nationkey").join(F.broadcast(small), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name", "r_name")


@_op("select o_orderkey, count(*) as n, sum(l_quantity) as quantity from lineitem join orders on l_orderkey = o_orderkey group by o_orderkey")
def op_join_sortmerge(spark, d):
    l, o = load(spark, d, "lineitem", "l_orderkey", "l_quantity"), load(spark, d, "orders", "o_orderkey")
    return l.join(o.hint("MERGE"), l.l_orderkey == o.o_orderkey).groupBy("o_orderkey").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


@_op("select p_brand, count(*) as n from lineitem join part on l_partkey = p_partkey group by p_brand")
def op_join_shuffle_hash(spark, d):
    l, p = load(spark, d, "lineitem", "l_partkey"), load(spark, d, "part", "p_partkey", "p_brand")
    return l.join(p.hint("SHUFFLE_HASH"), l.l_partkey == p.p_partkey).groupBy("p_brand").agg(F.count("*").alias("n"))


_POINTS = "(select o_orderkey as id, o_totalprice / 1000.0 as x, date_diff('day', date '1995-01-01', o_orderdate::date)::double as y from orders)"


@_op(f"with p as {_POINTS}, q as (select * from p order by md5(id || '|1'), id limit 5) select q.id as query_id, p.id as obj_id from q, p where sqrt((p.x - q.x) * (p.x - q.x) + (p.y - q.y) * (p.y - q.y)) <= 25.0000137")
def op_join_cross_theta(spark, d):
    p = objects(spark, d, "order_points")
    q = pick(p, 5).select(F.col("obj_id").alias("query_id"), F.col("obj").alias("q"))
    near = columns.euclid(F.col("obj.x"), F.col("obj.y"), F.col("q.x"), F.col("q.y")) <= 25.0000137
    return p.join(F.broadcast(q), near).select("query_id", "obj_id")


@_op("with w as (select i, timestamp '2024-01-01' + i * interval 7 day as a, timestamp '2024-01-01' + (i + 1) * interval 7 day as b from range(0, 6) t(i)) select event_id, i::bigint as week from events join w on ts >= a and ts < b")
def op_join_range(spark, d):
    w = spark.range(6).selectExpr("id as week", "timestamp_ntz '2024-01-01' + make_dt_interval(cast(id * 7 as int)) as a", "timestamp_ntz '2024-01-01' + make_dt_interval(cast((id + 1) * 7 as int)) as b")
    e = load(spark, d, "events", "event_id", "ts")
    return e.join(F.broadcast(w), (e.ts >= w.a) & (e.ts < w.b)).select("event_id", "week")


@_op("select e.event_id, coalesce(p.event_id, -1) as earlier from (select event_id, user_id, ts from events where event_type = (select min(event_type) from events)) e asof left join (select event_id, user_id, ts from events where event_type = (select max(event_type) from events)) p on e.user_id = p.user_id and e.ts >= p.ts")
def op_join_asof(spark, d):
    e = load(spark, d, "events", "event_id", "user_id", "ts", "event_type")
    ends = F.broadcast(e.agg(F.min("event_type").alias("lo"), F.max("event_type").alias("hi")))
    rows = e.join(ends).where((F.col("event_type") == F.col("lo")) | (F.col("event_type") == F.col("hi")))
    rows = rows.withColumn("right", F.col("event_type") == F.col("hi"))
    order = Window.partitionBy("user_id").orderBy("ts", F.desc("right")).rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumn("earlier", F.last(F.when(F.col("right"), F.col("event_id")), ignorenulls=True).over(order)).where("not right").select("event_id", F.coalesce("earlier", F.lit(-1)).alias("earlier"))


@_op("select a.event_id as first_id, b.event_id as second_id from events a join events b on a.user_id = b.user_id and a.event_id <> b.event_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour")
def op_join_interval(spark, d):
    e = load(spark, d, "events", "event_id", "user_id", "ts")
    a, b = e.toDF("first_id", "user_id", "ta"), e.toDF("second_id", "user_id", "tb")
    return a.join(b, "user_id").where("first_id <> second_id and tb > ta and tb <= ta + interval 1 hour").select("first_id", "second_id")


@_op("select c_custkey from customer where c_custkey in (select o_custkey from orders)")
def op_semi(spark, d):
    return load(spark, d, "customer", "c_custkey").join(load(spark, d, "orders", F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_semi")


@_op("select c_custkey from customer where c_custkey not in (select o_custkey from orders)")
def op_anti(spark, d):
    return load(spark, d, "customer", "c_custkey").join(load(spark, d, "orders", F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti")


@_op("select n_nationkey, count(s_suppkey) as n from nation left join supplier on n_nationkey = s_nationkey group by n_nationkey")
def op_left_outer(spark, d):
    n, s = load(spark, d, "nation", "n_nationkey"), load(spark, d, "supplier", "s_suppkey", "s_nationkey")
    return n.join(s, n.n_nationkey == s.s_nationkey, "left").groupBy("n_nationkey").agg(F.count("s_suppkey").alias("n"))


@_op("select coalesce(d.doc_id, l.doc_id) as doc_id, coalesce(l.quality, -1) as quality, coalesce(d.n_chars, -1) as n_chars from documents d full join labels l on d.doc_id = l.doc_id")
def op_full_outer(spark, d):
    return load(spark, d, "documents", "doc_id", "n_chars").join(load(spark, d, "labels", "doc_id", "quality"), "doc_id", "full").select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"), F.coalesce("n_chars", F.lit(-1)).alias("n_chars"))


@_op("select c_custkey, o_orderkey from customer, lateral (select o_orderkey from orders where o_custkey = c_custkey order by o_orderdate desc, o_orderkey limit 3)")
def op_lateral_topk(spark, d):
    o = load(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    top = o.withColumn("rn", F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_orderdate"), "o_orderkey"))).where("rn <= 3")
    return load(spark, d, "customer", "c_custkey").join(top, F.col("c_custkey") == F.col("o_custkey")).select("c_custkey", "o_orderkey")


@_op("select l_returnflag, l_linestatus, count(*) as n, sum(l_quantity) as quantity, max(l_extendedprice) as dearest from lineitem group by all")
def op_agg_hash(spark, d):
    return load(spark, d, "lineitem", "l_returnflag", "l_linestatus", "l_quantity", "l_extendedprice").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"), F.max("l_extendedprice").alias("dearest"))


@_op("select event_type, count(distinct user_id) as users from events group by event_type")
def op_agg_distinct(spark, d):
    return load(spark, d, "events", "event_type", "user_id").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@_op(None)
def op_agg_approx_distinct(spark, d):
    return load(spark, d, "events", "event_type", "user_id").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"))


@_op("select l_partkey, len(list(l_shipdate order by l_shipdate))::bigint as n, list_min(list(l_quantity)) as least from lineitem group by l_partkey")
def op_agg_collect(spark, d):
    g = load(spark, d, "lineitem", "l_partkey", "l_shipdate", "l_quantity").groupBy("l_partkey").agg(F.array_sort(F.collect_list(F.struct("l_shipdate", "l_quantity"))).alias("v"))
    return g.select("l_partkey", F.size("v").cast("long").alias("n"), F.array_min("v.l_quantity").alias("least"))


@_op(f"with p as {_POINTS}, c as (select * from p order by md5(id || '|1'), id limit 8) select p.id as obj_id, arg_min(c.id, (sqrt((p.x - c.x) * (p.x - c.x) + (p.y - c.y) * (p.y - c.y)), c.id)) as center from p, c group by p.id")
def op_agg_argmin(spark, d):
    p = objects(spark, d, "order_points")
    c = F.broadcast(pick(p, 8).select(F.col("obj_id").alias("cid"), F.col("obj").alias("c")))
    dist = columns.euclid(F.col("obj.x"), F.col("obj.y"), F.col("c.x"), F.col("c.y"))
    return p.join(c).groupBy("obj_id").agg(F.min_by("cid", F.struct(dist.alias("d"), "cid")).alias("center"))


@_op("select event_type, percentile_cont(0.25) within group (order by value) as q1, percentile_cont(0.5) within group (order by value) as q2 from events group by event_type")
def op_agg_percentile(spark, d):
    return load(spark, d, "events", "event_type", "value").groupBy("event_type").agg(F.percentile("value", F.lit(0.25)).alias("q1"), F.percentile("value", F.lit(0.5)).alias("q2"))


@_op("select event_type, round(stddev_samp(value), 6) as sd, round(avg(value), 6) as mean, min(value) as lo, max(value) as hi from events group by event_type")
def op_agg_stats(spark, d):
    return load(spark, d, "events", "event_type", "value").groupBy("event_type").agg(F.round(F.stddev("value"), 6).alias("sd"), F.round(F.avg("value"), 6).alias("mean"), F.min("value").alias("lo"), F.max("value").alias("hi"))


_SETS = "select status, priority, coalesce(yr, 0) as yr, count(*) as n from (select o_orderstatus as status, o_orderpriority as priority, year(o_orderdate)::bigint as yr from orders) group by "


def _orders(spark, d):
    return load(spark, d, "orders", F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority"), _year("o_orderdate").alias("yr"))


def _filled(df):
    return df.withColumn("yr", F.coalesce("yr", F.lit(0)))


@_op(_SETS + "rollup (status, priority, yr)")
def op_rollup_sets(spark, d):
    return _filled(_orders(spark, d).rollup("status", "priority", "yr").agg(F.count("*").alias("n")))


@_op(_SETS + "cube (status, priority, yr)")
def op_cube(spark, d):
    return _filled(_orders(spark, d).cube("status", "priority", "yr").agg(F.count("*").alias("n")))


@_op(_SETS + "grouping sets ((status, priority), (yr), ())")
def op_grouping_sets(spark, d):
    o = _orders(spark, d)
    return _filled(o.groupingSets([[o.status, o.priority], [o.yr], []], "status", "priority", "yr").agg(F.count("*").alias("n")))


@_op("select (date_diff('day', date '2024-01-01', ts::date) // 7)::bigint as week, " + ", ".join(f"count(*) filter (event_type = '{t}') as n_{t}" for t in ("click", "view")) + " from events group by week")
def op_pivot(spark, d):
    e = load(spark, d, "events", "ts", "event_type").select(F.floor(F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")) / 7).alias("week"), "event_type")
    p = e.groupBy("week").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1)))
    return p.select("week", F.coalesce("click", F.lit(0)).cast("long").alias("n_click"), F.coalesce("view", F.lit(0)).cast("long").alias("n_view"))


@_op("unpivot (select l_orderkey, l_partkey, l_suppkey, l_linenumber, l_shipdate, l_quantity as quantity, l_discount as discount from lineitem where l_orderkey <= 200) on quantity, discount into name measure value amount")
def op_unpivot(spark, d):
    keys = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_shipdate"]
    rows = load(spark, d, "lineitem", *keys, "l_quantity", "l_discount").where("l_orderkey <= 200").withColumnsRenamed({"l_quantity": "quantity", "l_discount": "discount"})
    return rows.unpivot(keys, ["quantity", "discount"], "measure", "amount")


@_op("unpivot (select l_orderkey, l_partkey, l_suppkey, l_linenumber, l_shipdate, l_quantity as quantity, l_discount as discount from lineitem) on quantity, discount into name measure value amount")
def op_unpivot_whole(spark, d):
    keys = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_shipdate"]
    rows = load(spark, d, "lineitem", *keys, "l_quantity", "l_discount").withColumnsRenamed({"l_quantity": "quantity", "l_discount": "discount"})
    return rows.unpivot(keys, ["quantity", "discount"], "measure", "amount")


@_op("select o_orderkey, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, ntile(4) over w as nt from orders window w as (partition by o_custkey order by o_totalprice, o_orderkey)")
def op_win_rank(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    o = load(spark, d, "orders", "o_orderkey", "o_custkey", "o_totalprice")
    return o.select("o_orderkey", *(f.over(w).cast("long").alias(n) for n, f in (("rn", F.row_number()), ("rk", F.rank()), ("dr", F.dense_rank()), ("nt", F.ntile(4)))))


@_op("select event_id, coalesce(epoch_us(ts) - epoch_us(lag(ts) over w), -1)::bigint as gap, round(coalesce(lead(value) over w - value, 0), 6) as rise from events window w as (partition by user_id order by ts, event_id)")
def op_win_lag_lead(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = load(spark, d, "events", "event_id", "user_id", "ts", "value").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.coalesce(F.col("us") - F.lag("us").over(w), F.lit(-1)).alias("gap"), F.round(F.coalesce(F.lead("value").over(w) - F.col("value"), F.lit(0.0)), 6).alias("rise"))


@_op("select l_partkey, epoch_us(l_shipdate) as t, sum(q) over w as x, (sum(c) over w)::double / 1000000.0 as y from (select l_partkey, l_shipdate, sum(l_quantity) as q, sum(round(l_extendedprice * 100)::bigint) as c from lineitem group by all) window w as (partition by l_partkey order by l_shipdate)")
def op_running_path(spark, d):
    from ..sources.objects import line_vertices

    return line_vertices(spark, d, "l_partkey")


@_op("select event_id, count(*) over w as n from events window w as (partition by user_id order by epoch_us(ts) range between 604800000000 preceding and current row)")
def op_win_range_frame(spark, d):
    e = load(spark, d, "events", "event_id", "user_id", "ts").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("us").rangeBetween(-604800000000, 0)).alias("n"))


@_op("select distinct user_id, first_value(event_id) over w as first_id, last_value(event_id) over w as last_id from events window w as (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following)")
def op_win_first_last(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return load(spark, d, "events", "event_id", "user_id", "ts").select("user_id", F.first("event_id").over(w).alias("first_id"), F.last("event_id").over(w).alias("last_id")).distinct()


@_op("select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 10")
def op_sort_limit(spark, d):
    return load(spark, d, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@_op("select o_orderkey from orders order by o_totalprice, o_orderkey limit 10 offset 25")
def op_topk_offset(spark, d):
    return load(spark, d, "orders", "o_orderkey", "o_totalprice").orderBy("o_totalprice", "o_orderkey").offset(25).limit(10).select("o_orderkey")


def _two_years(spark, d):
    o = load(spark, d, "orders", "o_custkey", "o_orderdate")
    return tuple(o.where(F.year("o_orderdate") == y).select("o_custkey") for y in (1996, 1997))


def _set_op(name: str, how: str, word: str):
    def run(spark, d):
        a, b = _two_years(spark, d)
        return {"union": lambda: a.union(b).distinct(), "union_all": lambda: a.union(b), "intersect": lambda: a.intersect(b), "intersect_all": lambda: a.intersectAll(b), "except": lambda: a.subtract(b), "except_all": lambda: a.exceptAll(b)}[how]()

    run.__name__ = name
    return _op(f"select o_custkey from orders where year(o_orderdate) = 1996 {word} select o_custkey from orders where year(o_orderdate) = 1997")(run)


for _how in ("union", "intersect", "except"):
    _set_op(f"op_{_how}", _how, _how)
    _set_op(f"op_{_how}_all", f"{_how}_all", f"{_how} all")


@_op("select count(*) as n, min(doc_id) as first_id from documents group by text")
def op_dedup(spark, d):
    return load(spark, d, "documents", "doc_id", "text").groupBy("text").agg(F.count("*").alias("n"), F.min("doc_id").alias("first_id")).select("n", "first_id")


@_op("select doc_id, lower(substr(text, 1, 20)) as head, length(text) as n, md5(text) as digest, replace(source, 'src', 's') as src from documents")
def op_str(spark, d):
    return load(spark, d, "documents", "doc_id", "text", "source").select("doc_id", F.lower(F.substring("text", 1, 20)).alias("head"), F.length("text").cast("long").alias("n"), F.md5("text").alias("digest"), F.replace("source", F.lit("src"), F.lit("s")).alias("src"))


@_op("select doc_id, regexp_extract(text, '([A-Za-z]+)[,.]', 1) as word, regexp_matches(text, '[0-9]') as digits, regexp_replace(source, '[a-z]+', '', 'g') as num from documents")
def op_regex(spark, d):
    return load(spark, d, "documents", "doc_id", "text", "source").select("doc_id", F.regexp_extract("text", "([A-Za-z]+)[,.]", 1).alias("word"), F.col("text").rlike("[0-9]").alias("digits"), F.regexp_replace("source", "[a-z]+", "").alias("num"))


@_op("select doc_id, " + ", ".join(f"(length(t) - length(replace(t, '{c}', '')))::double as n_{c}" for c in "aeiou") + " from (select doc_id, lower(text) as t from documents)")
def op_letters(spark, d):
    at = {c: "abcdefghijklmnopqrstuvwxyz".index(c) for c in "aeiou"}
    return objects(spark, d, "letter_hist").select(F.col("obj_id").alias("doc_id"), *(F.col("obj")[i].alias(f"n_{c}") for c, i in at.items()))


@_op("select o_orderkey, date_diff('day', date '1995-01-01', o_orderdate::date) as days, (date_trunc('month', o_orderdate)::date)::varchar as month, year(o_orderdate)::bigint as yr from orders")
def op_date(spark, d):
    day = F.to_date("o_orderdate")
    return load(spark, d, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", F.datediff(day, F.lit("1995-01-01").cast("date")).cast("long").alias("days"), F.trunc(day, "month").cast("string").alias("month"), _year("o_orderdate").alias("yr"))


@_op("select event_id, round(sqrt(value), 6) as root, round(asinh(value), 6) as arc, greatest(value, 100.0) as hi, least(value, 100.0) as lo, floor(value / 10)::bigint as bin, abs(value - 250) as away from events")
def op_math(spark, d):
    v = F.col("value")
    return load(spark, d, "events", "event_id", "value").select("event_id", F.round(F.sqrt(v), 6).alias("root"), F.round(F.asinh(v), 6).alias("arc"), F.greatest(v, F.lit(100.0)).alias("hi"), F.least(v, F.lit(100.0)).alias("lo"), F.floor(v / 10).alias("bin"), F.abs(v - 250).alias("away"))


@_op("select vec_id, round(list_sum(list_transform(embedding, lambda x: abs(x::double))), 5) as l1, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 5) as dot, embedding[1] as head, len(embedding[3:10])::bigint as part from embeddings")
def op_array(spark, d):
    e = F.col("embedding").cast("array<double>")
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda t, x: t + x)
    return load(spark, d, "embeddings", "vec_id", "embedding").select("vec_id", F.round(total(F.transform(e, F.abs)), 5).alias("l1"), F.round(total(F.transform(e, lambda x: x * x)), 5).alias("dot"), F.col("embedding")[0].alias("head"), F.size(F.slice("embedding", 3, 8)).cast("long").alias("part"))


@_op("select user_id, event_type as k, count(*) as v from events group by all")
def op_map(spark, d):
    g = load(spark, d, "events", "user_id", "event_type").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = g.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.explode(F.map_entries("m")).alias("e")).select("user_id", F.col("e.key").alias("k"), F.col("e.value").alias("v"))


@_op("select event_id, (props->>'k')::bigint as k, (props->>'k')::bigint as k2, (props->>'k')::bigint as k3 from events")
def op_json_k(spark, d):
    p = F.col("props")
    return load(spark, d, "events", "event_id", "props").select("event_id", F.get_json_object(p, "$.k").cast("long").alias("k"), F.from_json(p, "k long")["k"].alias("k2"), F.variant_get(F.parse_json(p), "$.k", "long").alias("k3"))


def _sql(spark, d, query: str, *tables: str) -> DataFrame:
    return spark.sql(query, **{t: load(spark, d, t) for t in tables})


@_op("select c_custkey from customer c where exists (select 1 from orders o where o.o_custkey = c.c_custkey and o.o_totalprice > 400000)")
def op_subquery_exists(spark, d):
    return _sql(spark, d, "select c_custkey from {customer} c where exists (select 1 from {orders} o where o.o_custkey = c.c_custkey and o.o_totalprice > 400000)", "customer", "orders")


@_op("select o_orderkey from orders o where o_totalprice > 1.5 * (select avg(o_totalprice) from orders p where p.o_custkey = o.o_custkey)")
def op_subquery_scalar(spark, d):
    return _sql(spark, d, "select o_orderkey from {orders} o where o_totalprice > 1.5 * (select avg(o_totalprice) from {orders} p where p.o_custkey = o.o_custkey)", "orders")


@_op("select p_partkey from part where p_partkey in (select l_partkey from lineitem where l_quantity >= 49)")
def op_subquery_in(spark, d):
    return _sql(spark, d, "select p_partkey from {part} where p_partkey in (select l_partkey from {lineitem} where l_quantity >= 49)", "part", "lineitem")


_TREE = "with recursive w(node, depth) as (select c_custkey::bigint, 0::bigint from customer where c_custkey < 3 union all select c.c_custkey::bigint, w.depth + 1 from w join customer c on c.c_custkey // 3 = w.node where c.c_custkey >= 3) select node, depth from w"


@_op(_TREE)
def op_cte_recursive(spark, d):
    """Customers as a tree of degree three, customer k below customer k div 3, level by level."""
    spark.conf.set("spark.sql.cteRecursionRowLimit", "-1")  # a table may have more rows than its million
    return _sql(spark, d, "with recursive w(node, depth) as (select cast(c_custkey as bigint), 0L from {customer} where c_custkey < 3 union all select cast(c.c_custkey as bigint), w.depth + 1 from w join {customer} c on c.c_custkey div 3 = w.node where c.c_custkey >= 3) select node, depth from w", "customer")


@_op("select o_orderkey from orders order by md5(o_orderkey || '|1'), o_orderkey limit 25")
def op_sample_md5(spark, d):
    return pick(load(spark, d, "orders", "o_orderkey"), 25, key="o_orderkey")


_VERTICES = """v as (select obj_id, case when hi > lo then (t - lo)::double / (hi - lo) else 0.0 end as s, x, y, hi > lo as moving from
  (select l_partkey as obj_id, t, x, y, min(t) over (partition by l_partkey) as lo, max(t) over (partition by l_partkey) as hi from
    (select l_partkey, epoch_us(l_shipdate) as t, sum(q) over w as x, (sum(c) over w)::double / 1000000.0 as y from
      (select l_partkey, l_shipdate, sum(l_quantity) as q, sum(round(l_extendedprice * 100)::bigint) as c from lineitem group by all)
      window w as (partition by l_partkey order by l_shipdate))))"""


@_op(f"with {_VERTICES}, e as (select obj_id, arg_min(x, s) as x0, arg_min(y, s) as y0, arg_max(x, s) as x1, arg_max(y, s) as y1 from v group by obj_id) select obj_id, round(max(sqrt((x - x0 - s * (x1 - x0)) * (x - x0 - s * (x1 - x0)) + (y - y0 - s * (y1 - y0)) * (y - y0 - s * (y1 - y0)))), 6) as radius from v join e using (obj_id) group by obj_id")
def op_udf_arrow(spark, d):
    radius = F.arrow_udf(register.hull_radius, "double")
    return objects(spark, d, "part_paths").select("obj_id", F.round(radius("obj"), 6).alias("radius"))


@_op("with p as (select a.label, a.vec_id, round(sum(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: abs(z[1]::double - z[2]::double)))), 6) as total from embeddings a join embeddings b on a.label = b.label group by a.label, a.vec_id) select label, arg_min(vec_id, (total, vec_id)) as medoid from p group by label")
def op_udaf(spark, d):
    def run(ids: pd.Series, vectors: pd.Series) -> int:
        return register.medoid(ids, vectors)

    return load(spark, d, "embeddings", "label", "vec_id", "embedding").groupBy("label").agg(F.pandas_udf(run, "long")("vec_id", "embedding").alias("medoid"))


@_op(f"with {_VERTICES} select obj_id, count(*) as n, round(sum(dx), 6) as run from (select obj_id, lead(x) over w - x as dx from v window w as (partition by obj_id order by s)) where dx is not null and obj_id <= 40 group by obj_id")
def op_udtf(spark, d):
    register.register_functions(spark)
    paths = objects(spark, d, "part_paths").where("obj_id <= 40 and size(obj.s) > 2")
    return spark.sql("select p.obj_id, count(*) as n, round(sum(u.x1 - u.x0), 6) as run from {p} p, lateral units(p.obj) u group by p.obj_id", p=paths)


@_op(f"with {_VERTICES} select obj_id, count(*) as n, round(sum(dx), 6) as run from (select obj_id, lead(x) over w - x as dx from v window w as (partition by obj_id order by s)) where dx is not null group by obj_id")
def op_udtf_whole(spark, d):
    register.register_functions(spark)
    return spark.sql("select p.obj_id, count(*) as n, round(sum(u.x1 - u.x0), 6) as run from {p} p, lateral units(p.obj) u group by p.obj_id", p=objects(spark, d, "part_paths"))


__all__ = ["ORACLES", "QUERIES", "movements"]
