"""Queries of the relational operators, formats and functions around the sketches, each with its SQL twin."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..config import portable
from ..operators import estimators, exact, registers
from ..sources import tables
from ..sources.tables import load, scratch, stored
from . import sqltext as q
from .registry import FLAGS, add, r6

# -- sources and sinks --------------------------------------------------------------------------


def formats_roundtrip(spark, d):
    """Distinct names of customers, written and read again in each format."""
    x, out = load(spark, d, "customer", ["c_custkey", "c_name", "c_mktsegment"]), None
    for fmt in ("parquet", "orc", "json", "csv", "text"):
        path = scratch(spark)
        (x.select("c_name") if fmt == "text" else x).write.format(fmt).save(path)
        y = tables.load_as(spark, fmt, path, None if fmt == "text" else x.schema)
        y = y.withColumnRenamed("value", "c_name") if fmt == "text" else y
        e = estimators.estimate(y, "c_name", portable(256), "nb").select(F.lit(fmt).alias("format"), r6())
        out = e if out is None else out.union(e)
    return out


add("formats_roundtrip", formats_roundtrip, f"select unnest(['parquet', 'orc', 'json', 'csv', 'text']) as format, estimate from ({q.estimate('nb', 'c_name', 'customer', 256)})")


def sql_views(spark, d):
    """The tables as views, queried in SQL."""
    tables.register(spark, d)
    return spark.sql("select r_name, count(distinct c_custkey) as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by r_name")


add("sql_views", sql_views, "select r_name, count(distinct c_custkey) as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by r_name")

# -- joins --------------------------------------------------------------------------------------


def range_join(spark, d):
    """Distinct users in the hour before and after each alert (an event of high value): events meet alerts by hour and then by
    interval, so that no pair is made of hours that are far apart."""
    e = load(spark, d, "events", ["event_id", "ts", "user_id", "value", "event_type"])
    alerts = e.where("event_type = 'error' and value > 200").select(F.col("event_id").alias("alert"), F.col("ts").alias("at"))
    hour = lambda c: F.date_trunc("hour", c)
    near = alerts.select("alert", "at", F.explode(F.array(*[hour(F.col("at") + F.expr(f"interval {h} hours")) for h in (-1, 0, 1)])).alias("hour"))
    x = near.join(e.select("ts", "user_id", hour("ts").alias("hour")), "hour").where("ts between at - interval 1 hour and at + interval 1 hour")
    return estimators.estimate(x, "user_id", portable(16), "nb", ["alert"]).select("alert", r6())


add("range_join", range_join, q.estimate("nb", "user_id", "(select a.event_id as alert, b.user_id from events a join events b on b.ts between a.ts - interval 1 hour and a.ts + interval 1 hour where a.event_type = 'error' and a.value > 200)", 16, ["alert"]))


def join_kinds(spark, d):
    """Rows of each kind of join of the customers with their orders of one year."""
    c = load(spark, d, "customer", ["c_custkey"])
    o = load(spark, d, "orders", ["o_custkey", "o_orderdate"]).where(F.year("o_orderdate") == 1995).select("o_custkey").distinct()
    out = None
    for kind in ("inner", "left", "right", "full", "left_semi", "left_anti"):
        e = c.join(o, F.col("c_custkey") == F.col("o_custkey"), kind).agg(F.lit(kind).alias("kind"), F.count("*").alias("n"))
        out = e if out is None else out.union(e)
    return out


_o95 = "(select distinct o_custkey from orders where extract(year from o_orderdate) = 1995)"
add("join_kinds", join_kinds, "\nunion all\n".join(f"select '{k}' as kind, count(*) as n from customer {j} join {_o95} on c_custkey = o_custkey" for k, j in (("inner", ""), ("left", "left"), ("right", "right"), ("full", "full"), ("left_semi", "semi"), ("left_anti", "anti"))))

# -- aggregation --------------------------------------------------------------------------------


def exact_many(spark, d):
    return exact.exact_many(load(spark, d, "lineitem", ["l_orderkey", "l_partkey", "l_suppkey", *FLAGS]), ["l_orderkey", "l_partkey", "l_suppkey"], FLAGS)


add("exact_many", exact_many, "select l_returnflag, l_linestatus, count(distinct l_orderkey) as n_l_orderkey, count(distinct l_partkey) as n_l_partkey, count(distinct l_suppkey) as n_l_suppkey from lineitem group by all")


def pivot_methods(spark, d):
    """Methods as columns, groups as rows."""
    s, out = stored(estimators.sums(registers.build(load(spark, d, "lineitem", ["l_partkey", "l_returnflag"]), "l_partkey", portable(256), ["l_returnflag"]), 256, ["l_returnflag"])), None
    for k in ("nb", "hll", "loglog", "pcsa"):
        e = estimators.from_sums(s, k, portable(256), ["l_returnflag"]).select("l_returnflag", "method", "estimate")
        out = e if out is None else out.union(e)
    return out.groupBy("l_returnflag").pivot("method", ["nb", "hll", "loglog", "pcsa"]).agg(F.round(F.first("estimate"), 6))


add("pivot_methods", pivot_methods, f"select l_returnflag, {', '.join(f'round({q.value(k, 256)}, 6) as {k}' for k in ('nb', 'hll', 'loglog', 'pcsa'))} from ({q.sums(q.cells('l_partkey', 'lineitem', 256, ['l_returnflag']), 256, ['l_returnflag'])})")


def basic_aggregates(spark, d):
    x = load(spark, d, "orders", ["o_orderkey", "o_orderpriority", "o_custkey"])
    return x.groupBy("o_orderpriority").agg(
        F.count("*").alias("n"), F.sum("o_custkey").alias("s"), F.round(F.avg("o_custkey"), 6).alias("mean"), F.min("o_custkey").alias("least"), F.max("o_custkey").alias("most"), F.round(F.var_pop("o_custkey"), 3).alias("var"),
        F.round(F.stddev("o_custkey"), 6).alias("sd"), F.min_by("o_custkey", "o_orderkey").alias("first_buyer"), F.max_by("o_custkey", "o_orderkey").alias("last_buyer"), F.count_if(F.col("o_custkey") % 2 == 0).alias("even"),
        F.round(F.median("o_custkey"), 3).alias("middle"), F.bool_or(F.col("o_custkey") > 1400).alias("any_high"), F.bit_xor("o_custkey").alias("mixed"))


add("basic_aggregates", basic_aggregates, """select o_orderpriority, count(*) as n, sum(o_custkey)::bigint as s, round(avg(o_custkey), 6) as mean, min(o_custkey) as least, max(o_custkey) as most, round(var_pop(o_custkey), 3) as var, round(stddev(o_custkey), 6) as sd,
min_by(o_custkey, o_orderkey) as first_buyer, max_by(o_custkey, o_orderkey) as last_buyer, count_if(o_custkey % 2 = 0)::bigint as even, round(median(o_custkey), 3) as middle, bool_or(o_custkey > 1400) as any_high, bit_xor(o_custkey) as mixed from orders group by 1""")

# -- windows, order, sets -----------------------------------------------------------------------


def ranking(spark, d):
    """Suppliers by distinct orders within each flag, under every ranking function."""
    e = estimators.estimate(load(spark, d, "lineitem", ["l_suppkey", "l_orderkey", "l_returnflag"]), "l_orderkey", portable(64), "nb", ["l_returnflag", "l_suppkey"]).select("l_returnflag", "l_suppkey", r6())
    w, total = Window.partitionBy("l_returnflag").orderBy(F.desc("estimate")), Window.partitionBy("l_returnflag").orderBy(F.desc("estimate"), "l_suppkey")
    return e.select("l_returnflag", "l_suppkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"), F.ntile(4).over(total).alias("quarter"))


_sup = q.estimate("nb", "l_orderkey", "lineitem", 64, ["l_returnflag", "l_suppkey"])
_w = "over (partition by l_returnflag order by estimate desc)"
add("ranking", ranking, f"select l_returnflag, l_suppkey, cast(rank() {_w} as integer) as r, cast(dense_rank() {_w} as integer) as dr, round(percent_rank() {_w}, 6) as pr, round(cume_dist() {_w}, 6) as cd, cast(ntile(4) over (partition by l_returnflag order by estimate desc, l_suppkey) as integer) as quarter from ({_sup})")


def analytic(spark, d):
    """Daily distinct users beside their neighbours in time."""
    x = load(spark, d, "events", ["ts", "user_id"]).withColumn("day", F.to_date("ts"))
    e = estimators.estimate(x, "user_id", portable(64), "nb", ["day"]).select("day", r6()).withColumn("g", F.lit(0))
    w = Window.partitionBy("g").orderBy("day")
    whole, three = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing), w.rowsBetween(-2, 0)
    return e.select("day", F.lead("estimate").over(w).alias("after"), F.lag("estimate", 2).over(w).alias("before"), F.first("estimate").over(whole).alias("first_day"), F.last("estimate").over(whole).alias("last_day"),
                    F.nth_value("estimate", 3).over(whole).alias("third"), F.round(F.avg("estimate").over(three), 6).alias("mean3"), F.max("estimate").over(three).alias("max3"))


_day = q.estimate("nb", "user_id", "(select cast(ts as date) as day, user_id from events)", 64, ["day"])
_all = "rows between unbounded preceding and unbounded following"
add("analytic", analytic, f"""select day, lead(estimate) over w as after, lag(estimate, 2) over w as before, first_value(estimate) over (order by day {_all}) as first_day, last_value(estimate) over (order by day {_all}) as last_day,
nth_value(estimate, 3) over (order by day {_all}) as third, round(avg(estimate) over (order by day rows between 2 preceding and current row), 6) as mean3, max(estimate) over (order by day rows between 2 preceding and current row) as max3 from ({_day}) window w as (order by day)""")


def set_operations(spark, d):
    """Buyers of two years under each set operation, with and without repeats."""
    x = load(spark, d, "orders", ["o_custkey", "o_orderdate"]).select("o_custkey", F.year("o_orderdate").alias("y"))
    a, b = (x.where(F.col("y") == y).select("o_custkey") for y in (1995, 1996))
    out = None
    for n, y in (("union_all", a.unionAll(b)), ("union", a.union(b).distinct()), ("by_name", a.unionByName(b)), ("intersect", a.intersect(b)), ("intersect_all", a.intersectAll(b)), ("except", a.subtract(b)), ("except_all", a.exceptAll(b))):
        e = y.agg(F.lit(n).alias("op"), F.count("*").alias("n"), F.sum("o_custkey").alias("s"))
        out = e if out is None else out.union(e)
    return out


_y = lambda y: f"select o_custkey from orders where extract(year from o_orderdate) = {y}"
add("set_operations", set_operations, "\nunion all\n".join(f"select '{n}' as op, count(*) as n, sum(o_custkey)::bigint as s from ({_y(1995)} {op} {_y(1996)})" for n, op in (("union_all", "union all"), ("union", "union"), ("by_name", "union all"), ("intersect", "intersect"), ("intersect_all", "intersect all"), ("except", "except"), ("except_all", "except all"))))


def sorted_limits(spark, d):
    """The ten dearest orders of all, and of each partition of the priorities the dearest."""
    x = load(spark, d, "orders", ["o_orderkey", "o_totalprice", "o_orderpriority"])
    top = x.orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select(F.lit("all").alias("scope"), "o_orderkey")
    first = x.repartition("o_orderpriority").sortWithinPartitions("o_orderpriority", F.desc("o_totalprice"), "o_orderkey").dropDuplicates(["o_orderpriority"])
    w = Window.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    each = x.withColumn("r", F.row_number().over(w)).where("r = 1").select(F.col("o_orderpriority").alias("scope"), "o_orderkey")
    return top.union(each).union(first.agg(F.lit("priorities").alias("scope"), F.count("*").alias("o_orderkey")))


add("sorted_limits", sorted_limits, """select 'all' as scope, o_orderkey from (select * from orders order by o_totalprice desc, o_orderkey limit 10)
union all select o_orderpriority, o_orderkey from (select *, row_number() over (partition by o_orderpriority order by o_totalprice desc, o_orderkey) as r from orders) where r = 1 union all select 'priorities', count(distinct o_orderpriority) from orders""")

# -- scalar functions ---------------------------------------------------------------------------


def scalar_strings(spark, d):
    x = load(spark, d, "customer", ["c_custkey", "c_name", "c_mktsegment"])
    n, s = F.col("c_name"), F.col("c_mktsegment")
    return x.select(
        "c_custkey", F.lower(n).alias("lo"), F.upper(n).alias("up"), F.trim(F.concat(F.lit("  "), n, F.lit(" "))).alias("tr"), F.get(F.split(n, "#"), F.lit(1)).alias("sp"), F.substring(n, 2, 4).alias("su"), F.length(n).alias("le"),
        F.concat_ws("-", n, s).alias("cw"), F.regexp_extract(n, "([0-9]+)", 1).alias("re"), F.regexp_replace(n, "0+", "0").alias("rr"), n.like("%1%").alias("li"), F.translate(s, "AEIOU", "aeiou").alias("ta"), F.reverse(s).alias("rv"),
        F.md5(n.cast("binary")).alias("md"), F.sha2(n.cast("binary"), 256).alias("sh"), F.conv(F.hex("c_custkey"), 16, 10).cast("long").alias("hx"), F.bin("c_custkey").alias("bi"), F.levenshtein(s, F.lit("BUILDING")).alias("lv"), F.instr(n, "#").alias("ins"),
        F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("lp"), F.initcap(F.lower(s)).alias("ic"), F.decode(F.unhex(F.hex(s.cast("binary"))), "UTF-8").alias("uh"), F.repeat(F.lit("ab"), 2).alias("rp"), n.startswith("C").alias("st"))


add("scalar_strings", scalar_strings, """select c_custkey, lower(c_name) as lo, upper(c_name) as up, trim('  ' || c_name || ' ') as tr, string_split(c_name, '#')[2] as sp, substr(c_name, 2, 4) as su, cast(length(c_name) as integer) as le, concat_ws('-', c_name, c_mktsegment) as cw,
regexp_extract(c_name, '([0-9]+)', 1) as re, regexp_replace(c_name, '0+', '0', 'g') as rr, c_name like '%1%' as li, translate(c_mktsegment, 'AEIOU', 'aeiou') as ta, reverse(c_mktsegment) as rv, md5(c_name) as md, sha256(c_name) as sh, c_custkey as hx, ltrim(bin(c_custkey), '0') || case when c_custkey = 0 then '0' else '' end as bi,
cast(levenshtein(c_mktsegment, 'BUILDING') as integer) as lv, cast(instr(c_name, '#') as integer) as ins, lpad(cast(c_custkey as varchar), 8, '0') as lp, upper(substr(c_mktsegment, 1, 1)) || lower(substr(c_mktsegment, 2)) as ic, c_mktsegment as uh, repeat('ab', 2) as rp, starts_with(c_name, 'C') as st from customer""")


def scalar_urls(spark, d):
    u = F.col("url")
    return load(spark, d, "pages", ["page_id", "url"]).select("page_id", F.parse_url(u, F.lit("HOST")).alias("host"), F.parse_url(u, F.lit("PROTOCOL")).alias("scheme"), F.coalesce(F.parse_url(u, F.lit("QUERY")), F.lit("")).alias("query"))


add("scalar_urls", scalar_urls, "select page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) as host, regexp_extract(url, '^([a-z]+)://', 1) as scheme, regexp_extract(url, '\\?([^#]*)', 1) as query from pages")


def scalar_dates(spark, d):
    t = F.col("o_orderdate")
    return load(spark, d, "orders", ["o_orderkey", "o_orderdate"]).select(
        "o_orderkey", F.to_date(t).alias("da"), F.to_date(F.date_trunc("month", t)).alias("mo"), F.year(t).alias("ye"), F.month(t).alias("mm"), F.dayofweek(t).alias("dw"), F.date_add(t, 40).alias("ad"), F.datediff(t, F.lit("1992-01-01").cast("date")).alias("dd"),
        F.unix_timestamp(t.cast("timestamp")).alias("ep"), F.date_format(F.timestamp_seconds(F.unix_timestamp(t.cast("timestamp")) + 3600), "yyyy-MM-dd HH:mm").alias("ho"), F.quarter(t).alias("qu"), F.last_day(t).alias("la"), F.weekofyear(t).alias("we"), F.to_date(F.add_months(t, 1)).alias("am"),
        F.date_format(F.window(t.cast("timestamp"), "7 days")["start"], "yyyy-MM-dd").alias("wi"))


add("scalar_dates", scalar_dates, """select o_orderkey, cast(o_orderdate as date) as da, cast(date_trunc('month', o_orderdate) as date) as mo, cast(year(o_orderdate) as integer) as ye, cast(month(o_orderdate) as integer) as mm, cast(dayofweek(o_orderdate) + 1 as integer) as dw, cast(cast(o_orderdate as date) + 40 as date) as ad,
cast(date_diff('day', date '1992-01-01', cast(o_orderdate as date)) as integer) as dd, cast(epoch(o_orderdate) as bigint) as ep, strftime(o_orderdate + interval 1 hour, '%Y-%m-%d %H:%M') as ho, cast(quarter(o_orderdate) as integer) as qu, last_day(o_orderdate) as la, cast(weekofyear(o_orderdate) as integer) as we,
cast(o_orderdate + interval 1 month as date) as am, strftime(cast('1970-01-01' as date) + cast(floor(date_diff('day', date '1970-01-01', cast(o_orderdate as date)) / 7) * 7 as integer), '%Y-%m-%d') as wi from orders""")


def scalar_math(spark, d):
    k = F.col("s_suppkey")
    return load(spark, d, "supplier", ["s_suppkey", "s_acctbal"]).select(
        "s_suppkey", F.round(F.pow(k.cast("double"), F.lit(0.5)), 6).alias("po"), F.round(F.log(k + 1.0), 6).alias("ln"), F.round(F.log2(k + 1.0), 6).alias("l2"), F.round(F.exp(k / 1000.0), 6).alias("ex"), F.round(F.sqrt(k.cast("double")), 6).alias("sq"), F.ceil(F.col("s_acctbal")).cast("long").alias("ce"), F.floor(F.col("s_acctbal")).cast("long").alias("fl"),
        F.greatest(k, F.lit(50).cast("long")).alias("gr"), F.least(k, F.lit(50).cast("long")).alias("ls"), F.pmod(-k, F.lit(7).cast("long")).alias("pm"), F.shiftleft(k, 3).alias("sl"), F.shiftright(k, 1).alias("sr"), F.shiftrightunsigned(k, 2).alias("su"), F.bit_count(k).alias("bc"),
        k.bitwiseAND(F.lit(12).cast("long")).alias("an"), k.bitwiseOR(F.lit(12).cast("long")).alias("orr"), k.bitwiseXOR(F.lit(12).cast("long")).alias("xo"), F.bitwise_not(k).alias("no"), F.signum(F.col("s_acctbal")).cast("int").alias("sg"), F.abs(F.col("s_acctbal")).alias("ab"))


add("scalar_math", scalar_math, """select s_suppkey, round(pow(s_suppkey, 0.5), 6) as po, round(ln(s_suppkey + 1), 6) as ln, round(log2(s_suppkey + 1), 6) as l2, round(exp(s_suppkey / 1000.0), 6) as ex, round(sqrt(s_suppkey), 6) as sq, cast(ceil(s_acctbal) as bigint) as ce, cast(floor(s_acctbal) as bigint) as fl,
greatest(s_suppkey, 50::bigint) as gr, least(s_suppkey, 50::bigint) as ls, ((-s_suppkey % 7) + 7) % 7 as pm, s_suppkey << 3 as sl, s_suppkey >> 1 as sr, s_suppkey >> 2 as su, cast(bit_count(s_suppkey) as integer) as bc, s_suppkey & 12 as an, s_suppkey | 12 as orr, xor(s_suppkey, 12::bigint) as xo, ~s_suppkey as no, cast(sign(s_acctbal) as integer) as sg, abs(s_acctbal) as ab from supplier""")


def scalar_arrays(spark, d):
    """Words of benchmark items as arrays."""
    x = load(spark, d, "benchmark", ["item_id", "text"]).select("item_id", F.split(F.lower("text"), " ").alias("w"))
    w, five = F.col("w"), F.slice("w", 1, 5)
    return x.select(
        "item_id", F.size(w).alias("n"), F.size(F.array_distinct(w)).alias("nd"), F.array_join(F.sort_array(five), "|").alias("so"), F.array_join(F.transform(five, lambda v, i: F.concat(v, i.cast("string"))), "|").alias("tf"), F.size(F.filter(w, lambda v: F.length(v) > 4)).alias("fi"),
        F.aggregate(w, F.lit(0), lambda a, v: a + F.length(v)).alias("ag"), F.array_join(F.zip_with(five, F.reverse(five), lambda a, b: F.concat(a, b)), "|").alias("zi"), F.size(F.array_union(five, F.slice("w", 3, 5))).alias("un"), F.size(F.array_intersect(five, F.slice("w", 3, 5))).alias("it"),
        F.aggregate(F.sequence(F.lit(1), F.size(w)), F.lit(0).cast("long"), lambda a, v: a + v).alias("sq"), F.size(F.flatten(F.array(five, five))).alias("fa"), F.exists(w, lambda v: v == "the").alias("ei"), F.array_max(five).alias("mx"), F.element_at(w, -1).alias("ea"))


add("scalar_arrays", scalar_arrays, """with x as (select item_id, string_split(lower(text), ' ') as w from benchmark), y as (select *, w[1:5] as f, w[3:7] as g from x)
select item_id, cast(len(w) as integer) as n, cast(len(list_distinct(w)) as integer) as nd, array_to_string(list_sort(f), '|') as so, array_to_string(list_transform(f, lambda v, i: v || (i - 1)), '|') as tf, cast(len(list_filter(w, lambda v: length(v) > 4)) as integer) as fi,
cast(list_sum(list_transform(w, lambda v: length(v))) as integer) as ag, array_to_string(list_transform(range(1, len(f) + 1), lambda i: f[i] || f[len(f) + 1 - i]), '|') as zi, cast(len(list_distinct(list_concat(f, g))) as integer) as un, cast(len(list_distinct(list_intersect(f, g))) as integer) as it,
cast(len(w) * (len(w) + 1) // 2 as bigint) as sq, cast(2 * len(f) as integer) as fa, list_contains(w, 'the') as ei, list_max(f) as mx, w[-1] as ea from y""")


def posexploded(spark, d):
    """Words by their place in a text: distinct texts at each of the first ten places."""
    x = load(spark, d, "documents", ["doc_id", "text"]).select("doc_id", F.posexplode(F.slice(F.split(F.lower("text"), " "), 1, 10)).alias("pos", "word"))
    return estimators.estimate(x, "word", portable(64), "nb", ["pos"]).select("pos", r6())


add("posexploded", posexploded, q.estimate("nb", "word", "(select cast(unnest(range(len(w))) as integer) as pos, unnest(w) as word from (select string_split(lower(text), ' ')[1:10] as w from documents))", 64, ["pos"]))


def scalar_maps(spark, d):
    """A sparse sketch as a map from cell to register, and back."""
    p = registers.pairs(registers.build(load(spark, d, "orders", ["o_custkey", "o_orderpriority"]), "o_custkey", portable(16), ["o_orderpriority"]), ["o_orderpriority"])
    m = p.groupBy("o_orderpriority").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("bucket", "top")))).alias("m"))
    m = m.select("o_orderpriority", F.map_concat("m", F.create_map(F.lit(99), F.lit(0).cast("tinyint"))).alias("m"))
    s = lambda x: F.aggregate(x, F.lit(0), lambda a, v: a + v.cast("int"))
    return m.select("o_orderpriority", F.size(F.map_keys("m")).alias("n"), s(F.map_values("m")).alias("s"), F.element_at("m", F.lit(3)).cast("int").alias("third"), F.size(F.map_entries(F.map_filter("m", lambda k, v: v > 5))).alias("high"))


_mp = f"select o_orderpriority, bucket, {q.TOP} as top from ({q.cells('o_custkey', 'orders', 16, ['o_orderpriority'])})"
add("scalar_maps", scalar_maps, f"select o_orderpriority, cast(count(*) + 1 as integer) as n, cast(sum(top) as integer) as s, cast(max(case when bucket = 3 then top end) as integer) as third, cast(count_if(top > 5) as integer) as high from ({_mp}) group by 1")


def scalar_json(spark, d):
    """Parsed and written again."""
    x = load(spark, d, "events", ["event_id", "user_id", "props"])
    x = x.select("event_id", F.from_json("props", "k int").alias("p"), F.get_json_object("props", "$.k").alias("g"), F.struct("event_id", F.col("user_id").alias("u")).alias("s"))
    return x.select("event_id", F.col("p.k").alias("k"), "g", F.to_json("s").alias("j"), F.col("s").getField("u").alias("u"), F.to_json(F.named_struct(F.lit("a"), F.col("p.k"))).alias("n"))


add("scalar_json", scalar_json, """select event_id, cast(json_extract(props, '$.k') as integer) as k, json_extract_string(props, '$.k') as g, '{"event_id":' || event_id || ',"u":' || user_id || '}' as j, user_id as u, '{"a":' || cast(json_extract(props, '$.k') as integer) || '}' as n from events""")


def scalar_nulls(spark, d):
    z = F.nullif(F.col("s_suppkey") % 3, F.lit(0))
    return load(spark, d, "supplier", ["s_suppkey", "s_name"]).select(
        "s_suppkey", F.coalesce(z, F.lit(-1).cast("long")).alias("co"), z.alias("nu"), F.when(z.isNull(), "none").when(z == 1, "one").otherwise("two").alias("ca"), z.isNull().alias("isn"), F.nvl(z, F.lit(9).cast("long")).alias("nv"), F.nvl2(z, F.lit("x"), F.lit("y")).alias("n2"),
        F.try_divide(F.lit(6.0), z).alias("td"), F.try_to_number("s_name", F.lit("999")).cast("int").alias("tn"), z.eqNullSafe(F.lit(None).cast("long")).alias("en"), F.expr("try_cast(s_name as int)").alias("tc"))


add("scalar_nulls", scalar_nulls, """select s_suppkey, coalesce(z, -1) as co, z as nu, case when z is null then 'none' when z = 1 then 'one' else 'two' end as ca, z is null as isn, ifnull(z, 9) as nv, case when z is not null then 'x' else 'y' end as n2, 6.0::double / z as td, try_cast(s_name as integer) as tn,
z is not distinct from null as en, try_cast(s_name as integer) as tc from (select *, nullif(s_suppkey % 3, 0) as z from supplier)""")


def element_wheres(spark, d):
    """Sketches of segments by each kind of condition."""
    x = load(spark, d, "part", ["p_partkey", "p_size", "p_brand", "p_type"])
    conditions = {"between": F.col("p_size").between(10, 20), "in": F.col("p_size").isin(1, 2, 3), "like": F.col("p_type").like("%STEEL"), "rlike": F.col("p_type").rlike("^(PROMO|SMALL)"), "not": ~(F.col("p_size") > 25), "or": (F.col("p_size") < 3) | (F.col("p_size") > 48)}
    e = estimators.from_sums(estimators.sums(registers.build_segments(x, "p_partkey", portable(64), conditions), 64, ["segment"]), "nb", portable(64), ["segment"])
    return e.select("segment", r6())


add("element_wheres", element_wheres, "\nunion all\n".join(f"select * from (select '{n}' as segment, estimate from ({q.estimate('nb', 'p_partkey', f'(select p_partkey from part where {w})', 64)})) where estimate > 0" for n, w in (("between", "p_size between 10 and 20"), ("in", "p_size in (1, 2, 3)"), ("like", "p_type like '%STEEL'"), ("rlike", "regexp_matches(p_type, '^(PROMO|SMALL)')"), ("not", "not p_size > 25"), ("or", "p_size < 3 or p_size > 48"))))
