"""Queries of the methods, their variants, baselines and workloads over the given tables.

Each has a SQL twin where DuckDB can express it.  Doubles are rounded in both.
"""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..config import SketchConfig, portable
from ..functions import sqlfuncs
from ..operators import codec, entropy, estimators, exact, martingale, measures, registers, setops, tailcut
from ..sources.tables import load, scratch, stored
from . import planner
from . import sqltext as q
from .registry import FLAGS, ORACLES, QUERIES, SIZES_SQL, add, each, r6, sizes  # noqa: F401

# -- mergeable sketches -----------------------------------------------------------------------

def _estimate(kind, table, col, m, by=(), threshold=2.5):
    def run(spark, d):
        cfg = portable(m, threshold=threshold)
        return estimators.estimate(load(spark, d, table, [col, *by]), col, cfg, kind, list(by)).select(*by, r6(), "regime")
    return run


for _k in ("nb", "hll"):
    add(f"{_k}_global", _estimate(_k, "lineitem", "l_orderkey", 256), q.estimate(_k, "l_orderkey", "lineitem", 256, more=f", {q.regime(_k, 256)} as regime"))
    add(f"{_k}_by_flag", _estimate(_k, "lineitem", "l_orderkey", 256, FLAGS), q.estimate(_k, "l_orderkey", "lineitem", 256, FLAGS, f", {q.regime(_k, 256)} as regime"))
    add(f"{_k}_small_range", _estimate(_k, "events", "user_id", 256), q.estimate(_k, "user_id", "events", 256, more=f", {q.regime(_k, 256)} as regime"))
add("nb_crossover", _estimate("nb", "orders", "o_custkey", 512), q.estimate("nb", "o_custkey", "orders", 512, more=f", {q.regime('nb', 512)} as regime"))
add("nb_crossover_tuned", _estimate("nb", "orders", "o_custkey", 512, (), 4.0), q.estimate("nb", "o_custkey", "orders", 512, more=f", {q.regime('nb', 512, 4.0)} as regime", threshold=4.0))
for _k in ("loglog", "pcsa"):
    add(f"{_k}_global", _estimate(_k, "lineitem", "l_orderkey", 256), q.estimate(_k, "l_orderkey", "lineitem", 256, more=", case when filled = 0 then 'empty' else 'raw' end as regime"))
add("pcsa_by_flag", _estimate("pcsa", "lineitem", "l_orderkey", 64, FLAGS), q.estimate("pcsa", "l_orderkey", "lineitem", 64, FLAGS, ", case when filled = 0 then 'empty' else 'raw' end as regime"))


def bitmap_single(spark, d):
    return estimators.bitmap_estimate(load(spark, d, "lineitem", ["l_orderkey", *FLAGS]), "l_orderkey", portable(1), FLAGS).select(*FLAGS, F.col("gap").cast("int").alias("gap"), r6())


add("bitmap_single", bitmap_single, f"select l_returnflag, l_linestatus, cast({q.GAP} as integer) as gap, round(pow(2.0::double, {q.GAP}) / {q.lit(q.PHI)}, 6) as estimate from ({q.cells('l_orderkey', 'lineitem', 1, FLAGS)})")


def nb_registers(spark, d):
    return registers.pairs(registers.build(load(spark, d, "lineitem", ["l_suppkey"]), "l_suppkey", portable(64)))


add("nb_registers", nb_registers, f"select cast(bucket as integer) as bucket, cast({q.TOP} as tinyint) as top, cast({q.NBR} as tinyint) as nbr from ({q.cells('l_suppkey', 'lineitem', 64)})")
add("hll_registers", lambda spark, d: nb_registers(spark, d).drop("nbr"), f"select cast(bucket as integer) as bucket, cast({q.TOP} as tinyint) as top from ({q.cells('l_suppkey', 'lineitem', 64)})")


def nb_init_cells(spark, d):
    """All cells, those that no element hit with their first values."""
    x = registers.pairs(registers.build(load(spark, d, "region", ["r_name"]), "r_name", portable(16)))
    return spark.range(16).select(F.col("id").cast("int").alias("bucket")).join(x, "bucket", "left").select("bucket", F.coalesce(F.col("top").cast("int"), F.lit(0)).alias("top"), F.coalesce(F.col("nbr").cast("int"), F.lit(1)).alias("nbr"))


add("nb_init_cells", nb_init_cells, f"select cast(r.range as integer) as bucket, cast(coalesce(top, 0) as integer) as top, cast(coalesce(nbr, 1) as integer) as nbr from range(16) r left join (select bucket, {q.TOP} as top, {q.NBR} as nbr from ({q.cells('r_name', 'region', 16)})) c on c.bucket = r.range")


def nb_change_probability(spark, d):
    s = registers.build(load(spark, d, "events", ["user_id", "event_type"]), "user_id", portable(256), ["event_type"])
    return estimators.change_probability(s, 256, ["event_type"])


add("nb_change_probability", nb_change_probability, f"select event_type, s_nb / 256 as q_nb, s_hll / 256 as q_hll from ({q.sums(q.cells('user_id', 'events', 256, ['event_type']), 256, ['event_type'])})")


def _merged(kind):
    def run(spark, d):
        """Monthly sketches, merged."""
        cfg, x = portable(256), load(spark, d, "lineitem", ["l_orderkey", "l_shipdate"]).withColumn("month", F.date_trunc("month", "l_shipdate"))
        s = registers.build(x, "l_orderkey", cfg, ["month"])
        return estimators.from_sums(estimators.sums(registers.merge([s.drop("month")]), 256), kind, cfg).select(r6())
    return run


for _k in ("nb", "hll"):
    add(f"{_k}_merge_shards", _merged(_k), q.estimate(_k, "l_orderkey", "lineitem", 256))


def nb_merge_pairs(spark, d):
    """Pairs of (top, nbr) of two halves of the rows, merged without their bitmaps."""
    cfg, x = portable(64), load(spark, d, "lineitem", ["l_orderkey", "l_linestatus"])
    parts = [registers.pairs(registers.build(x, "l_orderkey", cfg, where=F.col("l_linestatus") == v)) for v in ("O", "F")]
    return registers.merge_pairs(parts)


add("nb_merge_pairs", nb_merge_pairs, f"select cast(bucket as integer) as bucket, cast({q.TOP} as tinyint) as top, cast({q.NBR} as tinyint) as nbr from ({q.cells('l_orderkey', 'lineitem', 64)})")


def nb_duplicates(spark, d):
    x = load(spark, d, "lineitem", ["l_orderkey"])
    return estimators.estimate(x.union(x).union(x.orderBy(F.col("l_orderkey").desc())), "l_orderkey", portable(256), "nb").select(r6())


add("nb_duplicates", nb_duplicates, q.estimate("nb", "l_orderkey", "lineitem", 256))


def nb_fold(spark, d):
    s = registers.build(load(spark, d, "lineitem", ["l_orderkey"]), "l_orderkey", portable(256))
    return estimators.from_sums(estimators.sums(registers.fold(s, 64), 64), "nb", portable(64)).select(r6())


add("nb_fold", nb_fold, q.estimate("nb", "l_orderkey", "lineitem", 64))


def nb_roundtrip(spark, d):
    """Packed at rest and unpacked: the registers again."""
    p = registers.pairs(registers.build(load(spark, d, "lineitem", ["l_suppkey", "l_returnflag"]), "l_suppkey", portable(64), ["l_returnflag"]), ["l_returnflag"])
    return codec.cells(codec.blobs(p, 64, "nb", ["l_returnflag"]), ["l_returnflag"]).drop("bitmap")


add("nb_roundtrip", nb_roundtrip, f"select l_returnflag, cast(bucket as integer) as bucket, cast({q.TOP} as tinyint) as top, cast({q.NBR} as tinyint) as nbr from ({q.cells('l_suppkey', 'lineitem', 64, ['l_returnflag'])})")

_Y = "extract(year from o_orderdate)"


def _years(spark, d):
    x = load(spark, d, "orders", ["o_custkey", "o_orderdate"]).withColumn("y", F.year("o_orderdate"))
    cfg = portable(512)
    return [registers.build(x, "o_custkey", cfg, where=F.col("y") == y) for y in (1995, 1996)], cfg


def nb_union_intersect(spark, d):
    (a, b), cfg = _years(spark, d)
    return setops.set_sizes(a, b, cfg).select(*[F.round(c, 6).alias(c) for c in ("n_a", "n_b", "n_union", "n_both", "n_only_a", "jaccard")])


_side = lambda w: f"(select {q.value('nb', 512)} from ({q.sums(q.cells('o_custkey', f'(select o_custkey from orders where {w})', 512), 512)}))"
add("nb_union_intersect", nb_union_intersect, f"""with v as (select {_side(f'{_Y} = 1995')} as a, {_side(f'{_Y} = 1996')} as b, {_side(f'{_Y} in (1995, 1996)')} as u)
select round(a, 6) as n_a, round(b, 6) as n_b, round(u, 6) as n_union, round(greatest(0.0, a + b - u), 6) as n_both, round(greatest(0.0, u - b), 6) as n_only_a, round(greatest(0.0, a + b - u) / u, 6) as jaccard from v""")


def overlap_exact(spark, d):
    x = load(spark, d, "orders", ["o_custkey", "o_orderdate"]).select("o_custkey", F.year("o_orderdate").alias("y"))
    a, b = [x.where(F.col("y") == y).select("o_custkey").distinct() for y in (1995, 1996)]
    return a.join(b, "o_custkey", "left_semi").agg(F.count("*").alias("n_both")).crossJoin(a.join(b, "o_custkey", "left_anti").agg(F.count("*").alias("n_only_a")))


add("overlap_exact", overlap_exact, f"""with a as (select distinct o_custkey from orders where {_Y} = 1995), b as (select distinct o_custkey from orders where {_Y} = 1996)
select count(*) filter (where o_custkey in (select o_custkey from b)) as n_both, count(*) filter (where o_custkey not in (select o_custkey from b)) as n_only_a from a""")


def nb_jaccard_segments(spark, d):
    x = load(spark, d, "orders", ["o_custkey", "o_orderpriority"])
    return setops.pairwise_jaccard(registers.build(x, "o_custkey", portable(256), ["o_orderpriority"]), "o_orderpriority", portable(256)).select("a", "b", r6("jaccard"))


_prio = q.cells("o_custkey", "orders", 256, ["o_orderpriority"])
add("nb_jaccard_segments", nb_jaccard_segments, f"""with s as ({_prio}), e as (select o_orderpriority as g, {q.value('nb', 256)} as v from ({q.sums('select * from s', 256, ['o_orderpriority'])})),
p as (select x.g as a, y.g as b, x.v as n_a, y.v as n_b from e x join e y on x.g < y.g),
c as (select a, b, bucket, bit_or(bitmap) as bitmap from p join s on s.o_orderpriority in (a, b) group by a, b, bucket),
u as (select a, b, {q.value('nb', 256)} as u from ({q.sums('select * from c', 256, ['a', 'b'])}))
select a, b, round(greatest(0.0, n_a + n_b - u) / u, 6) as jaccard from p join u using (a, b)""")

# -- sequential and lossy sketches ------------------------------------------------------------
ORDER = ["o_orderdate", "o_orderkey"]


def _ordered(spark, d, *more):
    """Orders with date and key as one long, so that first arrivals aggregate by hash."""
    return load(spark, d, "orders", ["o_custkey", *ORDER, *more]).withColumn("at", martingale.packed_order(F.col("o_orderdate"), F.col("o_orderkey")))


def _mart(kind, by=()):
    def run(spark, d):
        return martingale.martingale(_ordered(spark, d, *by), "o_custkey", ["at"], portable(64), kind, list(by)).select(*by, "changes", F.round("est", 6).alias("est"), F.round("var", 4).alias("var"))
    return run


for _k in ("nb", "hll", "pcsa", "loglog"):
    add(f"mart_{_k}", _mart(_k), q.martingale(_k, "o_custkey", "orders", ORDER, 64))
add("mart_nb_by_priority", _mart("nb", ["o_orderpriority"]), q.martingale("nb", "o_custkey", "orders", ORDER, 64, ["o_orderpriority"]))


def _event_trace(spark, d):
    x = load(spark, d, "events", ["user_id", "ts", "event_id"])
    return martingale.trace(martingale.first_seen(x, "user_id", ["event_id"], portable(64)), portable(64), "nb")


add("mart_trace", lambda spark, d: _event_trace(spark, d).select(F.col("ord").alias("event_id"), "bucket", "bit", F.round("q_before", 9).alias("q_before")),
    f"select (ord).v as event_id, cast(bucket as integer) as bucket, bit, round(q, 9) as q_before from ({q.trace('nb', 'user_id', 'events', ['event_id'], 64).replace('min(row(event_id))', 'min(struct_pack(v := event_id))')})")


def mart_checkpoints(spark, d):
    points = load(spark, d, "events", ["event_id"]).where("event_id % 100 = 0").select(F.col("event_id").alias("at"))
    return martingale.trace_at(_event_trace(spark, d), points).select("checkpoint", r6("est"))


add("mart_checkpoints", mart_checkpoints, f"""with t as ({q.trace('nb', 'user_id', 'events', ['event_id'], 64).replace('min(row(event_id))', 'min(struct_pack(v := event_id))')})
select e.event_id as checkpoint, round(sum(1 / q), 6) as est from events e join t on (t.ord).v <= e.event_id where e.event_id % 100 = 0 group by e.event_id""")


def _snapshot(kind, width=4):
    def run(spark, d):
        s = registers.build(load(spark, d, "lineitem", ["l_extendedprice"]).select(F.round(F.col("l_extendedprice") * 100).cast("long").alias("cents")), "cents", portable(64))
        return tailcut.snapshot(s, portable(64), kind, width).select(r6())
    return run


for _k in ("nb", "hll"):
    _c = q.cells("cents", "(select cast(round(l_extendedprice * 100) as bigint) as cents from lineitem)", 64)
    for _w, _n in ((4, f"tc_{_k}_snapshot"), (2, f"tc_{_k}_snapshot_2bit")):
        add(_n, _snapshot(_k, _w), f"""with p as (select {q.TOP} as top, {q.NBR} as nbr from ({_c})), b as (select case when count(*) < 64 then 0 else min(top) end as base from p),
        d as (select least(top, base + {(1 << _w) - 1}) as top, nbr from p, b) select round({q.value(_k, 64)}, 6) as estimate from ({q.sums('select * from d', 64, top='top', nbr='nbr', gap='0')})""")


def _sequential(kind, width=4):
    def run(spark, d):
        return tailcut.estimate(tailcut.sequential(_ordered(spark, d), "o_custkey", ["at"], portable(64), kind, width), portable(64), kind).select("method", r6())
    return run


for _k in ("nb", "hll"):
    for _w, _n in ((4, f"tc_{_k}_sequential"), (2, f"tc_{_k}_sequential_2bit")):
        _t = f"select t as top, n as nbr from ({q.tail_cut('o_custkey', 'orders', ORDER, 64, _w)}) where t > 0"
        add(_n, _sequential(_k, _w), f"select 'tc_{_k}' as method, round({q.value(_k, 64)}, 6) as estimate from ({q.sums(_t, 64, top='top', nbr='nbr', gap='0')})")


def tc_merge_divergence(spark, d):
    """Cells in which merged halves, cut to two bits, differ from the whole stream cut so."""
    cfg, x = portable(64), _ordered(spark, d)
    halves = [tailcut.sequential(x.where(c), "o_custkey", ["at"], cfg, "nb", 2) for c in ("o_orderkey % 2 = 0", "o_orderkey % 2 = 1")]
    one = tailcut.sequential(x, "o_custkey", ["at"], cfg, "nb", 2)
    both = tailcut.merge_cells(*[h.select("bucket", F.col("top").cast("tinyint"), F.col("nbr").cast("tinyint")) for h in halves], 64, 2)
    y = one.select("bucket", F.struct("top", "nbr").alias("a")).join(both.select("bucket", F.struct(F.col("top").cast("int").alias("top"), F.col("nbr").cast("int").alias("nbr")).alias("b")), "bucket", "full")
    return y.agg(F.count("*").alias("cells"), F.sum((~F.col("a").eqNullSafe(F.col("b"))).cast("long")).alias("differ"))


_halves = [q.tail_cut("o_custkey", f"(select * from orders where o_orderkey % 2 = {i})", ORDER, 64, 2) for i in (0, 1)]
_mask = "case when t > 0 then 1::bigint << (t - 1) else 0 end | case when t > 1 and n = 1 then 1::bigint << (t - 2) else 0 end"
add("tc_merge_divergence", tc_merge_divergence, f"""with one as (select i, t, n from ({q.tail_cut('o_custkey', 'orders', ORDER, 64, 2)}) where t > 0),
bits as (select i, bit_or({_mask}) as bitmap from (select * from ({_halves[0]}) union all select * from ({_halves[1]})) where t > 0 group by i),
p as (select i, {q.TOP} as t, {q.NBR} as n from bits), b as (select case when count(*) < 64 then 0 else min(t) end as base from p),
both_ as (select i, least(t, base + 3) as t, n from p, b)
select count(*) as cells, sum(cast(one.t is distinct from both_.t or one.n is distinct from both_.n as bigint))::bigint as differ from one full join both_ on one.i = both_.i""")


def entropy_levels(spark, d):
    return entropy.levels(registers.build(load(spark, d, "lineitem", ["l_orderkey"]), "l_orderkey", portable(256)), depth=24)


add("entropy_levels", entropy_levels, f"select cast(r.range as integer) as level, sum((bitmap >> (r.range - 1)) & 1)::bigint as cells from range(1, 25) r, ({q.cells('l_orderkey', 'lineitem', 256)}) group by 1")


def entropy_bits(spark, d):
    est, bits = entropy.entropy_estimate(registers.build(load(spark, d, "lineitem", ["l_orderkey"]), "l_orderkey", portable(256)), 256)
    return spark.createDataFrame([("l_orderkey", 256, est, bits, bits / 256)], "name string, m int, estimate double, bits double, bits_a_cell double")


_level = f"select list(s order by k) as s from (select r.range as k, sum((bitmap >> (r.range - 1)) & 1)::double as s from range(1, 61) r, ({q.cells('l_orderkey', 'lineitem', 256)}) group by 1)"
_ll = lambda x: f"list_sum(list_transform(range(1, 61), lambda k: case when s[k] > 0 then s[k] * ln(1 - exp(-exp({x}) / (256 * pow(2.0::double, k)))) else 0 end - (256 - s[k]) * exp({x}) / (256 * pow(2.0::double, k))))"
add("entropy_bits", lambda spark, d: entropy_bits(spark, d).select("name", "m", F.round("estimate", 1).alias("estimate"), F.round("bits", 3).alias("bits"), F.round("bits_a_cell", 5).alias("bits_a_cell")), f"""with recursive l as ({_level}),
f(i, a, b) as (select 0, ln(1000.0::double), ln(1e8::double) union all
  select i + 1, case when p < r then a + (b - a) / 3 else a end, case when p < r then b else b - (b - a) / 3 end from (select i, a, b, {_ll('(a + (b - a) / 3)')} as p, {_ll('(b - (b - a) / 3)')} as r from f, l) where i < 70)
select 'l_orderkey' as name, 256 as m, round(exp((a + b) / 2), 1) as estimate, round(-{_ll('((a + b) / 2)')} / ln(2), 3) as bits, round(-{_ll('((a + b) / 2)')} / ln(2) / 256, 5) as bits_a_cell from f, l where i = 70""")

# -- exact counts and the engine's own ---------------------------------------------------------
add("exact_distinct", lambda spark, d: exact.exact_distinct(load(spark, d, "lineitem", ["l_orderkey", *FLAGS]), "l_orderkey", FLAGS), "select l_returnflag, l_linestatus, count(distinct l_orderkey) as n from lineitem group by all")
add("builtin_approx", lambda spark, d: exact.builtin_approx(load(spark, d, "lineitem", ["l_orderkey"]), "l_orderkey"))
add("builtin_hll", lambda spark, d: exact.builtin_hll(load(spark, d, "lineitem", ["l_orderkey"]), "l_orderkey"))


def native_hash(spark, d):
    """The default hash, all methods from one scan."""
    return estimators.all_estimates(load(spark, d, "lineitem", ["l_orderkey"]), "l_orderkey", SketchConfig(1024))


add("native_hash", native_hash)


def sql_functions(spark, d):
    sqlfuncs.register(spark)
    load(spark, d, "lineitem", ["l_orderkey"]).createOrReplaceTempView("lineitem_keys")
    return spark.sql(sqlfuncs.distinct_sql("lineitem_keys", "l_orderkey", 1024))


add("sql_functions", sql_functions)

# -- workloads ----------------------------------------------------------------------------------
PROFILED = {"lineitem": ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"], "orders": ["o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority"],
            "customer": ["c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment"], "supplier": ["s_suppkey", "s_name", "s_nationkey", "s_acctbal"], "part": ["p_partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice"], "events": ["event_id", "ts", "user_id", "event_type", "value", "props"],
            "nation": ["n_nationkey", "n_name", "n_regionkey"], "region": ["r_regionkey", "r_name"], "documents": ["doc_id", "text", "lang", "source", "n_chars"], "pages": ["page_id", "url", "html"], "benchmark": ["item_id", "text"], "labels": ["doc_id", "quality", "toxic"],
            "conversations": ["conv_id", "turn", "role", "text"], "embeddings": ["vec_id", "embedding", "label"]}


def _text_of(c, kind):
    """A column as text that both engines write alike."""
    if kind == "double":
        return F.round(F.col(c) * 100).cast("long").cast("string")
    if kind.startswith("timestamp"):
        return F.date_format(c, "yyyy-MM-dd HH:mm:ss.SSSSSS")
    if kind.startswith("array"):
        return F.array_join(F.transform(c, lambda v: F.floor(v.cast("double") * 1000000).cast("string")), ",")
    return F.col(c).cast("string")


def _text_sql(c):
    if c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax", "o_totalprice", "c_acctbal", "s_acctbal", "p_retailprice", "value"):
        return f"cast(cast(round({c} * 100) as bigint) as varchar)"
    if c in ("l_shipdate", "o_orderdate", "ts"):
        return f"strftime({c}, '%Y-%m-%d %H:%M:%S.%f')"
    if c == "embedding":
        return "array_to_string(list_transform(embedding, lambda v: cast(cast(floor(v::double * 1000000) as bigint) as varchar)), ',')"
    return f"cast({c} as varchar)"


def ndv_profile(spark, d):
    """Distinct values of every column of every table: a scan a table."""
    out = None
    for t, cols in PROFILED.items():
        x = load(spark, d, t, cols)
        x = x.select(*[_text_of(c, k).alias(c) for c, k in x.dtypes])
        x = planner.profile(x, cols, portable(256)).select(F.lit(t).alias("tab"), "name", r6())
        out = x if out is None else out.union(x)
    return out


add("ndv_profile", ndv_profile, "\nunion all\n".join(f"select '{t}' as tab, '{c}' as name, * from ({q.estimate('nb', _text_sql(c), t, 256)})" for t, cs in PROFILED.items() for c in cs))


def join_sizes(spark, d):
    """Rows of equi-joins from distinct counts of both sides' keys, beside the true number."""
    out = None
    for left, a, right, b in (("lineitem", "l_orderkey", "orders", "o_orderkey"), ("orders", "o_custkey", "customer", "c_custkey"), ("lineitem", "l_suppkey", "supplier", "s_suppkey")):
        x, y = load(spark, d, left, [a]), load(spark, d, right, [b])
        e = planner.join_estimate(x, a, y, b, portable(1024))
        n = x.join(y, F.col(a) == F.col(b)).agg(F.count("*").alias("n"))
        e = e.crossJoin(F.broadcast(n)).select(F.lit(f"{a}={b}").alias("keys"), F.round("rows", 3).alias("rows"), "n")
        out = e if out is None else out.union(e)
    return out


add("join_sizes", join_sizes, "\nunion all\n".join(f"""select '{a}={b}' as keys, round(nl * nr / greatest(dl, dr, 1.0), 3) as rows, n from (select estimate as dl from ({q.estimate('nb', a, left, 1024, digits=15)})), (select estimate as dr from ({q.estimate('nb', b, right, 1024, digits=15)})),
(select count(*)::double as nl from {left}), (select count(*)::double as nr from {right}), (select count(*) as n from {left} join {right} on {a} = {b})"""
    for left, a, right, b in (("lineitem", "l_orderkey", "orders", "o_orderkey"), ("orders", "o_custkey", "customer", "c_custkey"), ("lineitem", "l_suppkey", "supplier", "s_suppkey"))))


def ndv_composite(spark, d):
    x = load(spark, d, "lineitem", ["l_partkey", "l_suppkey"])
    e = estimators.estimate(x, ["l_partkey", "l_suppkey"], portable(256), "nb")
    return e.crossJoin(exact.exact_distinct(x, ["l_partkey", "l_suppkey"])).select(r6(), "n")


add("ndv_composite", ndv_composite, f"select estimate, n from ({q.estimate('nb', 'k', f"(select {q.composite('l_partkey', 'l_suppkey')} as k from lineitem)", 256)}), (select count(distinct (l_partkey, l_suppkey)) as n from lineitem)")


def flows_hour(spark, d):
    """Distinct (user, props) flows of each event type and hour."""
    x = load(spark, d, "events", ["ts", "event_type", "user_id", "props"]).withColumn("hour", F.date_trunc("hour", "ts"))
    return estimators.estimate(x, ["user_id", "props"], portable(64), "nb", ["event_type", "hour"]).select("event_type", "hour", r6())


_flow = f"(select event_type, date_trunc('hour', ts) as hour, {q.composite('user_id', 'props')} as k from events)"
add("flows_hour", flows_hour, q.estimate("nb", "k", _flow, 64, ["event_type", "hour"]))


def flows_alert(spark, d):
    """Hours whose flows exceed their type's mean by three deviations."""
    e = flows_hour(spark, d)
    w = Window.partitionBy("event_type")
    x = e.withColumn("mean", F.avg("estimate").over(w)).withColumn("sd", F.stddev_pop("estimate").over(w))
    return x.where("estimate > mean + 3 * sd").select("event_type", "hour", "estimate")


add("flows_alert", flows_alert, f"with e as ({ORACLES['flows_hour']}), w as (select *, avg(estimate) over (partition by event_type) as mean, stddev_pop(estimate) over (partition by event_type) as sd from e) select event_type, hour, estimate from w where estimate > mean + 3 * sd")
add("supplier_fanout", lambda spark, d: estimators.estimate(load(spark, d, "lineitem", ["l_orderkey", "l_suppkey"]), "l_orderkey", portable(64), "nb", ["l_suppkey"]).select("l_suppkey", r6()), q.estimate("nb", "l_orderkey", "lineitem", 64, ["l_suppkey"]))


def url_hosts(spark, d):
    x = load(spark, d, "pages", ["url"]).select(F.regexp_extract("url", r"^[a-z]+://([^/:]+)", 1).alias("host"), "url")
    return estimators.estimate(x, "url", portable(64), "nb", ["host"]).select("host", r6())


add("url_hosts", url_hosts, q.estimate("nb", "url", "(select regexp_extract(url, '^[a-z]+://([^/:]+)', 1) as host, url from pages)", 64, ["host"]))


def _per_word(table, key):
    def run(spark, d):
        """The 100 words found under most keys; ties go by the word."""
        x = load(spark, d, table, [key, "text"]).select(key, F.explode(F.array_distinct(F.split(F.lower("text"), " "))).alias("word"))
        return estimators.estimate(x, key, portable(64), "nb", ["word"]).select("word", r6()).orderBy(F.desc("estimate"), "word").limit(100)
    return run


for _n, _t, _key in (("docs_per_word_topk", "documents", "doc_id"), ("convs_per_word_topk", "conversations", "conv_id")):
    add(_n, _per_word(_t, _key), f"{q.estimate('nb', _key, f'(select {_key}, unnest(string_split(lower(text), chr(32))) as word from {_t})', 64, ['word'])} order by estimate desc, word limit 100")


def region_distinct(spark, d):
    """Customers who ordered, by region: the small tables are broadcast by their size."""
    x = load(spark, d, "orders", ["o_custkey"]).join(load(spark, d, "customer", ["c_custkey", "c_nationkey"]), F.col("o_custkey") == F.col("c_custkey"))
    x = x.join(load(spark, d, "nation", ["n_nationkey", "n_regionkey"]), F.col("c_nationkey") == F.col("n_nationkey")).join(load(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return estimators.estimate(x, "o_custkey", portable(256), "nb", ["r_name"]).select("r_name", r6())


_chain = "(select r_name, o_custkey from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey)"
add("region_distinct", region_distinct, q.estimate("nb", "o_custkey", _chain, 256, ["r_name"]))


def _joined(hint):
    def run(spark, d):
        """Distinct parts in each order year, under a given join strategy."""
        o = load(spark, d, "orders", ["o_orderkey", "o_orderdate"]).select("o_orderkey", F.year("o_orderdate").alias("y"))
        x = load(spark, d, "lineitem", ["l_orderkey", "l_partkey"]).join(o.hint(hint), F.col("l_orderkey") == F.col("o_orderkey"))
        return estimators.estimate(x, "l_partkey", portable(256), "nb", ["y"]).select("y", r6())
    return run


_oy = q.estimate("nb", "l_partkey", "(select cast(extract(year from o_orderdate) as integer) as y, l_partkey from lineitem join orders on l_orderkey = o_orderkey)", 256, ["y"])
for _h in ("merge", "shuffle_hash"):
    add(f"join_{_h}", _joined(_h), _oy)
SETS = {"segment_rollup": [FLAGS, FLAGS[:1], []], "segment_cube": [FLAGS, FLAGS[:1], FLAGS[1:], []], "grouping_sets": [FLAGS[:1], FLAGS[1:]]}
for _n, _sets in SETS.items():
    add(_n, lambda spark, d, s=_sets: planner.distinct_cube(load(spark, d, "lineitem", ["l_orderkey", *FLAGS]), "l_orderkey", FLAGS, portable(256), s).select(*FLAGS, "set_id", r6()),
        "\nunion all\n".join(f"select {', '.join(c if c in g else f'cast(null as varchar) as {c}' for c in FLAGS)}, {i} as set_id, estimate from ({q.estimate('nb', 'l_orderkey', 'lineitem', 256, g)})" for i, g in enumerate(_sets)))


def rolling7(spark, d):
    """Distinct users of the seven days up to each day: daily sketches, spread over the days they count in."""
    day = load(spark, d, "events", ["ts", "user_id"]).withColumn("day", F.to_date("ts"))
    s = registers.build(day, "user_id", portable(64), ["day"])
    last = s.agg(F.max("day").alias("last"))
    x = s.select(F.explode(F.sequence("day", F.date_add("day", 6))).alias("day"), "bucket", "bitmap").join(F.broadcast(last), F.col("day") <= F.col("last")).drop("last")
    m = x.groupBy("day", "bucket").agg(F.bit_or("bitmap").alias("bitmap"))
    return estimators.from_sums(estimators.sums(m, 64, ["day"]), "nb", portable(64), ["day"]).select("day", r6())


_spread = "(select cast(unnest(generate_series(cast(ts as date), cast(ts as date) + interval 6 day, interval 1 day)) as date) as day, user_id from events)"
add("rolling7", rolling7, f"select * from ({q.estimate('nb', 'user_id', _spread, 64, ['day'])}) where day <= (select max(cast(ts as date)) from events)")


def growth_lag(spark, d):
    x = load(spark, d, "events", ["ts", "user_id", "event_type"]).withColumn("day", F.to_date("ts"))
    e = estimators.estimate(x, "user_id", portable(64), "nb", ["event_type", "day"])
    w = Window.partitionBy("event_type").orderBy("day")
    return e.select("event_type", "day", r6(), F.round(F.col("estimate") - F.lag("estimate").over(w), 6).alias("growth"))


_daily = f"select event_type, day, {q.value('nb', 64)} as v from ({q.sums(q.cells('user_id', '(select event_type, cast(ts as date) as day, user_id from events)', 64, ['event_type', 'day']), 64, ['event_type', 'day'])})"
add("growth_lag", growth_lag, f"select event_type, day, round(v, 6) as estimate, round(v - lag(v) over (partition by event_type order by day), 6) as growth from ({_daily})")


def top_groups_rank(spark, d):
    e = estimators.estimate(load(spark, d, "lineitem", ["l_suppkey", "l_orderkey", "l_returnflag"]), "l_orderkey", portable(64), "nb", ["l_returnflag", "l_suppkey"]).select("l_returnflag", "l_suppkey", r6())
    w = Window.partitionBy("l_returnflag").orderBy(F.desc("estimate"), "l_suppkey")
    return e.withColumn("rn", F.row_number().over(w)).where("rn <= 10")


add("top_groups_rank", top_groups_rank, f"select * from (select *, row_number() over (partition by l_returnflag order by estimate desc, l_suppkey) as rn from ({q.estimate('nb', 'l_orderkey', 'lineitem', 64, ['l_returnflag', 'l_suppkey'])})) where rn <= 10")


def near_copies(spark, d):
    """Distinct texts, as they are and with case and spacing evened out."""
    x = load(spark, d, "documents", ["text", "lang"]).withColumn("even", F.regexp_replace(F.lower("text"), "[^a-z0-9]+", " "))
    a = estimators.estimate(x, "text", portable(256), "nb", ["lang"]).select("lang", r6())
    b = estimators.estimate(x, "even", portable(256), "nb", ["lang"]).select("lang", F.round("estimate", 6).alias("evened"))
    return a.join(b, "lang")


add("near_copies", near_copies, f"select lang, a.estimate, b.estimate as evened from ({q.estimate('nb', 'text', 'documents', 256, ['lang'])}) a join ({q.estimate('nb', 't', '(select lang, regexp_replace(lower(text), ' + chr(39) + '[^a-z0-9]+' + chr(39) + ', chr(32), ' + chr(39) + 'g' + chr(39) + ') as t from documents)', 256, ['lang'])}) b using (lang)")


def embeddings_distinct(spark, d):
    x = load(spark, d, "embeddings", ["embedding", "label"])
    return estimators.estimate(x, "embedding", SketchConfig(1024), "nb").crossJoin(x.select("embedding").distinct().agg(F.count("*").alias("n")))


add("embeddings_distinct", embeddings_distinct)
add("props_json", lambda spark, d: estimators.estimate(load(spark, d, "events", ["props", "event_type"]).withColumn("k", F.get_json_object("props", "$.k").cast("long")), "k", portable(64), "nb", ["event_type"]).select("event_type", r6()),
    q.estimate("nb", "k", "(select event_type, cast(json_extract(props, '$.k') as bigint) as k from events)", 64, ["event_type"]))

# -- measures and experiments -------------------------------------------------------------------


def memory_bits(spark, d):
    """Bits of a part's sketch by each method, and of all lines' that have as many cells."""
    of = lambda m, lines: [(k, m, b, lines, b * lines) for k in _MEM for b in (estimators.memory_bits(k, m),)]
    return each(sizes(spark, d), of, "method string, m int, bits long, lines long, all_bits long")


_MEM = {"pcsa": "64 * m", "loglog": "6 * m", "hll": "6 * m", "nb": "7 * m", "tc_hll": "4 * m + 6", "tc_nb": "5 * m + 6", "mart_hll": "6 * m + 64", "mart_nb": "7 * m + 64"}
add("memory_bits", memory_bits, "\nunion all\n".join(f"select '{k}' as method, cast(m as integer) as m, ({b})::bigint as bits, lines, (({b}) * lines)::bigint as all_bits from {SIZES_SQL}" for k, b in _MEM.items()))


def mvp_table1(spark, d):
    """Published memory-variance products beside those of the lines' sketches, of as many cells as these have."""
    of = lambda m, lines: [(k, m, lines, p, round(measures.mvp(k, m), 3)) for k, p in measures.PUBLISHED.items()]
    return each(sizes(spark, d), of, "method string, m int, lines long, published double, computed double")


_products = {"pcsa": (38.9, "64 * 0.78 * 0.78"), "loglog": (10.11, "6 * 1.69"), "hll": (6.48, "6 * m * (h1 / (h0 * h0) - 1)"), "nb": (5.46, "7 * m * (i1 / (i0 * i0) - 1)"), "entropy": (1.98, "4.69922 / 2.37326")}
add("mvp_table1", mvp_table1, q.integrals(SIZES_SQL) + "\nunion all\n".join(f"\nselect '{k}' as method, cast(m as integer) as m, lines, {p}::double as published, round(({c})::double, 3) as computed from i" for k, (p, c) in _products.items()))
_pairs = [("nb", "hll"), ("mart_nb", "mart_hll"), ("tc_nb", "tc_hll")]


def memory_ratios(spark, d):
    """The bits with which two methods count the lines of a flag and status to within their square root, and their ratio."""
    x, out = load(spark, d, "lineitem", FLAGS).groupBy(*FLAGS).agg(F.count("*").alias("n")), None
    for a, b in _pairs:
        bits = [F.lit(measures.mvp(k)) * F.col("n") for k in (a, b)]
        y = x.select(F.lit(a).alias("a"), F.lit(b).alias("b"), *FLAGS, "n", F.round(bits[0], 2).alias("bits_a"), F.round(bits[1], 2).alias("bits_b"), F.round(bits[0] / bits[1], 4).alias("ratio"))
        out = y if out is None else out.union(y)
    return out


_nb, _hll = "(41 * ln(2) / 16 - 1)", "(3 * ln(2) - 1)"
_ratio = {("nb", "hll"): (f"7 * {_nb}", f"6 * {_hll}"), ("mart_nb", "mart_hll"): ("7 * 0.75 * ln(2)", "6 * ln(2)"), ("tc_nb", "tc_hll"): (f"5 * {_nb}", f"4 * {_hll}")}
add("memory_ratios", memory_ratios, "\nunion all\n".join(
    f"select '{a}' as a, '{b}' as b, {', '.join(FLAGS)}, count(*) as n, round({x} * count(*), 2) as bits_a, round({y} * count(*), 2) as bits_b, round(({x}) * count(*) / (({y}) * count(*)), 4) as ratio from lineitem group by {', '.join(FLAGS)}" for (a, b), (x, y) in _ratio.items()))


def ablation_m(spark, d):
    """The neighbour bit on and off, and the number of cells, against the truth."""
    x, out = load(spark, d, "lineitem", ["l_orderkey"]), None
    s = stored(registers.build(x, "l_orderkey", portable(1024)))
    n = exact.exact_distinct(x, "l_orderkey")
    for m in (64, 128, 256, 512, 1024):
        t = estimators.sums(registers.fold(s, m), m)
        for k in ("nb", "hll"):
            e = estimators.from_sums(t, k, portable(m)).select("method", "m", "estimate", "rse")
            out = e if out is None else out.union(e)
    return out.crossJoin(F.broadcast(n)).select("method", "m", r6(), F.round("rse", 6).alias("rse"), "n", F.round(F.col("estimate") / F.col("n") - 1, 6).alias("error"))


_abl = "\nunion all\n".join(f"select '{k}' as method, {m} as m, round({q.value(k, m)}, 6) as estimate, round({q.rse(k, m)}, 6) as rse, n, round({q.value(k, m)} / n - 1, 6) as error from ({q.sums(q.cells('l_orderkey', 'lineitem', m), m)}), (select count(distinct l_orderkey) as n from lineitem)" for m in (64, 128, 256, 512, 1024) for k in ("nb", "hll"))
add("ablation_m", ablation_m, _abl)


def ablation_hash(spark, d):
    x = load(spark, d, "lineitem", ["l_orderkey"])
    return estimators.estimate(x, "l_orderkey", SketchConfig(256), "nb").select(F.lit("xxhash64").alias("family"), "estimate").union(estimators.estimate(x, "l_orderkey", portable(256), "nb").select(F.lit("md5"), "estimate"))


add("ablation_hash", ablation_hash)


def daily_store(spark, d):
    """Daily sketches at rest, a fortnight merged from them."""
    store = planner.SketchStore(spark, scratch(spark), portable(64), ["event_type"])
    store.write(load(spark, d, "events", ["ts", "user_id", "event_type"]), "user_id", F.col("ts"))
    return store.answer("2024-01-05", "2024-01-18", ["event_type"]).select("event_type", r6())


add("daily_store", daily_store, q.estimate("nb", "user_id", "(select event_type, user_id from events where cast(ts as date) between date '2024-01-05' and date '2024-01-18')", 64, ["event_type"]))
