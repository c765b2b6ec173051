"""Queries of measures, theory, simulations, replays, packed sketches and streams.

Simulated queries have no SQL twin: their draws differ from run to run of another engine.  Tests hold them against
the published numbers.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from ..config import SketchConfig, portable
from ..functions import theory
from ..functions.constants import alpha, gamma, variance
from ..functions.hashing import split
from ..operators import codec, estimators, exact, martingale, measures, registers, tailcut
from ..operators.blobs import register as register_blobs
from ..sources import simulate, streams
from ..sources.tables import load, scratch, stored
from ..streaming import windows
from . import sqltext as q
from .registry import FLAGS, SIZES_SQL, add, each, r6, sizes

# -- constants and theory -----------------------------------------------------------------------
def constants_table(spark, d):
    """The constants of the lines' sketches, and how many lines have them."""
    of = lambda m, lines: [(m, lines, *(round(v, 3) for v in (gamma(m), gamma(m, "laplace"), variance("nb", m), alpha(m), variance("hll", m))))]
    return each(sizes(spark, d), of, "m int, lines long, gamma double, gamma_laplace double, beta double, alpha double, hll_variance double")


add("constants_table", constants_table, f"""{q.integrals(SIZES_SQL)}
select cast(m as integer) as m, lines, round(1 / (m * i0), 3) as gamma, round(1 / (m * (3 * ln(2) / (2 * m)) * (1 + (41 * ln(2) / 16 - 1) / m)), 3) as gamma_laplace, round(m * (i1 / (i0 * i0) - 1), 3) as beta, round(1 / (m * h0), 3) as alpha, round(m * (h1 / (h0 * h0) - 1), 3) as hll_variance from i""")


def pair_law(spark, d):
    """The joint law of register and bit, as a product and as it is, of a cell that gets the lines of an order, and the
    orders with as many lines."""
    x = load(spark, d, "lineitem", ["l_orderkey"]).groupBy("l_orderkey").agg(F.count("*").cast("int").alias("n")).groupBy("n").agg(F.count("*").alias("orders"))
    of = lambda n, orders: [(k, s, n, orders, theory.p_pair(k, s, n), theory.p_pair_printed(k, s, n)) for k in range(1, 9) for s in (0, 1)]
    return each(x, of, "k int, seen int, n int, orders long, law double, product double").select("k", "seen", "n", "orders", r6("law", 9), r6("product", 9))


_top = "(pow(1 - pow(2.0::double, -k), n) - pow(1 - pow(2.0::double, 1 - k), n))"
_gone = "pow(1 - pow(2.0::double, 1 - k), n)"
add("pair_law", pair_law, f"""with g as (select cast(k.range as integer) as k, cast(s.range as integer) as seen, cast(n as integer) as n, orders from range(1, 9) k, range(2) s, (select n, count(*) as orders from (select count(*) as n from lineitem group by l_orderkey) group by n)),
t as (select *, {_top} as top, case when k = 1 then 0.0 else pow(1 - 3 * pow(2.0::double, -k), n) - pow(1 - 4 * pow(2.0::double, -k), n) end as unseen from g)
select k, seen, n, orders, round(case when seen = 0 then unseen else top - unseen end, 9) as law, round(top * case when seen = 1 then 1 - {_gone} else {_gone} end, 9) as product from t""")


def integrand_forms(spark, d):
    """The transform of a cell that gets the quantity of a line on average, as printed and simplified, beside its limit,
    and the lines of that quantity."""
    from ..functions.constants import f_nb

    x = load(spark, d, "lineitem", ["l_quantity"]).where("l_quantity > 0").groupBy(F.col("l_quantity").cast("double").alias("x")).agg(F.count("*").alias("lines"))
    of = lambda x, lines: [(x, lines, u, *(round(float(v), 7) for v in (theory.integrand(x, u, "printed"), theory.integrand(x, u), f_nb(u)))) for u in (0.1, 0.5, 1.0, 3.0)]
    return each(x, of, "x double, lines long, u double, printed double, simplified double, f double")


_sum = lambda q2: f"sum((exp(-x * s) - exp(-2 * x * s)) * exp(-u * x * s) + (exp(-x * (3 * s - 2 * {q2})) - exp(-x * (4 * s - 4 * {q2}))) * (exp(-3 * u * x * s) - exp(-u * x * s)))"
add("integrand_forms", integrand_forms, f"""with g as (select x, lines, u, pow(2.0::double, -k.range) as s from (select l_quantity::double as x, count(*) as lines from lineitem where l_quantity > 0 group by l_quantity), (select unnest([0.1::double, 0.5, 1.0, 3.0]) as u), range(1, 80) k)
select x, lines, u, round({_sum('s * s')}, 7) as printed, round({_sum('0')}, 7) as simplified, round({q.F_NB}, 7) as f from g group by x, lines, u""")


def mean_error(spark, d):
    """The error of the mean's integral for the lines' sketches, which stays under the stated bound."""
    return each(sizes(spark, d), lambda m, lines: [(m, lines, float(theory.mean_error(m)), 8.4e-5)], "m int, lines long, error double, bound double")


add("mean_error", mean_error)

# -- simulations --------------------------------------------------------------------------------
#: Streams and elements of the registered plots: enough streams to tell the order of each pair at 3 standard errors.
FULL = {"streams": 4000, "cells": 1024, "n": 1e6, "checkpoints": 4}
for _p in "abc":
    add(f"sim_fig1_{_p}", lambda spark, d, p=_p: simulate.plot_errors(spark, p, **FULL))
    add(f"sim_ratio_{_p}", lambda spark, d, p=_p: simulate.plot_ratio(spark, p, streams=8000, cells=256, n=2e5, checkpoints=1))


def sim_literal(spark, d):
    """Literal streams: 400 of 20,000 elements each, every element hashed."""
    cfg = SketchConfig(64)
    cells = simulate.literal(spark, 400, 20_000, cfg).groupBy("stream_id", "bucket").agg(F.bit_or("bit").alias("bitmap"))
    s = estimators.sums(cells, 64, ["stream_id"])
    x = None
    for k in ("nb", "hll", "loglog", "pcsa"):
        e = estimators.from_sums(s, k, cfg, ["stream_id"]).select("method", "estimate", "lo", "hi", F.lit(20_000.0).alias("truth"))
        x = e if x is None else x.union(e)
    x = stored(x)
    return measures.accuracy(x, "truth", ["method"]).join(measures.coverage(x, "truth", ["method"]), "method")


add("sim_literal", sim_literal)
add("mvp_measured", streams.measured_products)
add("retrospective_variance", streams.own_variances)
add("order_sensitivity", streams.order_share)


def ablation_width(spark, d):
    """Offsets of 2 to 5 bits, over the streams of all suppliers."""
    return streams.width_errors(spark, d)


add("ablation_width", ablation_width)


def update_cost(spark, d):
    rows = measures.update_cost(load(spark, d, "lineitem", ["l_orderkey"]), "l_orderkey", SketchConfig(1024))
    return spark.createDataFrame(rows, "method string, n_rows long, seconds double, rows_per_second double")


add("update_cost", update_cost)

# -- replays of given columns -------------------------------------------------------------------
SEEDS, POINTS = 32, 4
REPLAYS = {"l_orderkey": ("lineitem", "l_orderkey"), "cents": ("orders", "o_orderkey"), "o_custkey": ("orders", "o_orderkey"), "event_id": ("events", "event_id")}
MERGEABLE, SEQUENTIAL = ("nb", "hll", "loglog", "pcsa"), ("nb", "hll")


def _replayed(spark, d, name):
    """(column value, order, last order) of a replayed column."""
    table, order = REPLAYS[name]
    x = load(spark, d, table)
    value = F.round(F.col("o_totalprice") * 100).cast("long") if name == "cents" else F.col(name)
    return x.select(value.alias("v"), F.expr(order).alias("o"))


def _replay(name, seeds=SEEDS, m=64):
    def run(spark, d):
        """Each method's errors over seeds at equal parts of the order, by one scan: the first arrivals of every seed
        are kept, from which all methods at all checkpoints are read.  Tail-cut sketches are cut at the checkpoint."""
        x, cfg = _replayed(spark, d, name), portable(m)
        last = x.agg(F.max("o").alias("z"))
        points = last.select(F.explode(F.sequence(F.lit(1), F.lit(POINTS))).alias("point"), "z").select("point", F.floor(F.col("z") * F.col("point") / POINTS).alias("upto"))
        s = split(x.distinct().withColumn("seed", F.explode(F.sequence(F.lit(1), F.lit(seeds)))), "v", cfg, ["seed"], [F.col("o").alias("ord")], seed=F.col("seed"))
        first = stored(s.groupBy("seed", "bucket", "bit").agg(F.min("ord").alias("ord")))
        at = first.join(F.broadcast(points), F.col("ord") <= F.col("upto"))
        cells = at.groupBy("seed", "point", "bucket").agg(F.bit_or("bit").alias("bitmap"))
        by = ["seed", "point"]
        sums, out = stored(estimators.sums(cells, m, by)), None
        for k in MERGEABLE:
            e = estimators.from_sums(sums, k, cfg, by).select(F.lit(k).alias("method"), *by, "estimate")
            out = e if out is None else out.union(e)
        cut = tailcut.clamp(registers.pairs(cells, by), m, 4, by)
        for k in SEQUENTIAL:
            out = out.union(tailcut.estimate(cut, cfg, k, by).select(F.lit(f"tc_{k}").alias("method"), *by, "estimate"))
            t = martingale.trace(first, cfg, k, ["seed"]).select("seed", "ord", "inc")
            e = t.join(F.broadcast(points), F.col("ord") <= F.col("upto")).groupBy(*by).agg(F.sum("inc").alias("estimate"))
            out = out.union(e.select(F.lit(f"mart_{k}").alias("method"), *by, "estimate"))
        truth = x.join(F.broadcast(points), F.col("o") <= F.col("upto")).groupBy("point").agg(F.countDistinct("v").alias("n"))
        y = out.join(F.broadcast(truth), "point")
        a = measures.accuracy(y, "n", ["method", "point"])
        return a.select("method", "point", "runs", F.round("bias", 6).alias("bias"), F.round("rel_mse", 8).alias("rel_mse"))
    return run


def _replay_sql(name, seeds=SEEDS, m=64):
    table, order = REPLAYS[name]
    v = "cast(round(o_totalprice * 100) as bigint)" if name == "cents" else name
    src = f"(select distinct {v} as v, {order} as o, s.range as seed from {table}, range(1, {seeds + 1}) s)"
    first = f"select seed, bucket, bit, min(o) as ord from ({q.hashed('v', src, m, ['seed'], 'seed', 'o, ')}) group by seed, bucket, bit"
    by = ["seed", "point"]
    parts = [f"select '{k}' as method, seed, point, {q.value(k, m)} as e from s" for k in MERGEABLE]
    tc = q.sums("select * from cut", m, by, top="top", nbr="nbr", gap="0")
    parts += [f"select 'tc_{k}' as method, seed, point, {q.value(k, m)} as e from ({tc})" for k in SEQUENTIAL]
    for k in SEQUENTIAL:
        parts.append(f"select 'mart_{k}' as method, seed, point, sum(1 / q) as e from ({q.changes(k, 'select * from f', 'ord', m, ['seed'])}) join p on ord <= upto group by seed, point")
    return f"""with f as materialized ({first}), p as (select r.range as point, cast(floor(z * r.range / {POINTS}) as bigint) as upto from (select max({order}) as z from {table}), range(1, {POINTS + 1}) r),
c as materialized (select seed, point, bucket, bit_or(bit) as bitmap from f join p on ord <= upto group by seed, point, bucket),
s as materialized ({q.sums('select * from c', m, by)}),
pr as (select seed, point, bucket, {q.TOP} as top, {q.NBR} as nbr from c), b as (select seed, point, case when count(*) < {m} then 0 else min(top) end as base from pr group by seed, point),
cut as (select seed, point, least(top, base + 15) as top, nbr from pr join b using (seed, point)),
t as (select point, count(distinct {v}) as n from {table} join p on {order} <= upto group by point), e as ({' union all '.join(parts)})
select method, cast(point as integer) as point, count(*) as runs, round(avg(e / n) - 1, 6) as bias, round(avg(pow(e / n - 1, 2)), 8) as rel_mse from e join t using (point) group by method, point"""


for _n in REPLAYS:
    add(f"replay_{_n}", _replay(_n), _replay_sql(_n))


def seeds_coverage(spark, d):
    """How often the stated interval of each seed holds the exact number."""
    x = load(spark, d, "lineitem", ["l_orderkey"]).distinct().withColumn("seed", F.explode(F.sequence(F.lit(1), F.lit(SEEDS))))
    cells = split(x, "l_orderkey", portable(64), ["seed"], seed=F.col("seed")).groupBy("seed", "bucket").agg(F.bit_or("bit").alias("bitmap"))
    s, n = stored(estimators.sums(cells, 64, ["seed"])), exact.exact_distinct(load(spark, d, "lineitem", ["l_orderkey"]), "l_orderkey")
    out = None
    for k in MERGEABLE:
        e = estimators.from_sums(s, k, portable(64), ["seed"])
        out = e if out is None else out.union(e)
    return measures.coverage(out.crossJoin(F.broadcast(n)), "n", ["method"]).select("method", F.round("coverage", 6).alias("coverage"))


_seeded = f"(select distinct l_orderkey as v, s.range as seed from lineitem, range(1, {SEEDS + 1}) s)"
_cells = f"select seed, bucket, bit_or(bit) as bitmap from ({q.hashed('v', _seeded, 64, ['seed'], 'seed')}) group by seed, bucket"
add("seeds_coverage", seeds_coverage, f"with s as ({q.sums(_cells, 64, ['seed'])}), n as (select count(distinct l_orderkey) as n from lineitem) " + " union all ".join(
    f"select '{k}' as method, round(avg(cast(e * (1 - 1.96 * {q.rse(k, 64)}) <= n and n <= e * (1 + 1.96 * {q.rse(k, 64)}) as integer)), 6) as coverage from (select {q.value(k, 64)} as e from s), n" for k in MERGEABLE))


def ablation_linear(spark, d):
    """Linear counting on and off, for few and many distinct values a cell."""
    out = None
    for t, c in (("events", "user_id"), ("orders", "o_custkey"), ("lineitem", "l_orderkey")):
        x = load(spark, d, t, [c])
        s, n = stored(estimators.sums(registers.build(x, c, portable(256)), 256)), exact.exact_distinct(x, c)
        for k in SEQUENTIAL:
            for on in (True, False):
                e = estimators.from_sums(s, k, portable(256, small_range=on)).crossJoin(F.broadcast(n))
                e = e.select(F.lit(c).alias("name"), "method", F.lit(on).alias("linear"), r6(), F.round(F.col("estimate") / F.col("n") - 1, 6).alias("error"))
                out = e if out is None else out.union(e)
    return out


add("ablation_linear", ablation_linear, "\nunion all\n".join(
    f"select '{c}' as name, '{k}' as method, {str(on).lower()} as linear, round(e, 6) as estimate, round(e / n - 1, 6) as error from (select {q.value(k, 256, on)} as e from ({q.sums(q.cells(c, t, 256), 256)})), (select count(distinct {c}) as n from {t})"
    for t, c in (("events", "user_id"), ("orders", "o_custkey"), ("lineitem", "l_orderkey")) for k in SEQUENTIAL for on in (True, False)))


def ablation_sample(spark, d):
    """Why samples don't count distinct values: a tenth of the rows, by hash, scaled up, beside a sketch of that tenth."""
    x = load(spark, d, "lineitem", ["l_orderkey", "l_partkey", "l_linenumber"])
    tenth = x.where(F.conv(F.substring(F.md5(F.concat_ws("|", "l_orderkey", "l_linenumber").cast("binary")), 1, 4), 16, 10).cast("long") % 10 == 0)
    out = None
    for c in ("l_orderkey", "l_partkey", "l_linenumber"):
        e = exact.exact_distinct(x, c).crossJoin(F.broadcast(exact.exact_distinct(tenth, c).withColumnRenamed("n", "sampled"))).crossJoin(F.broadcast(estimators.estimate(tenth, c, portable(256), "nb").select("estimate")))
        e = e.select(F.lit(c).alias("name"), "n", "sampled", (F.col("sampled") * 10).alias("scaled"), r6())
        out = e if out is None else out.union(e)
    return out


_tenth = "(select * from lineitem where cast('0x' || substr(md5(l_orderkey || '|' || l_linenumber), 1, 4) as bigint) % 10 = 0)"
add("ablation_sample", ablation_sample, "\nunion all\n".join(f"select '{c}' as name, n, sampled, sampled * 10 as scaled, estimate from (select count(distinct {c}) as n from lineitem), (select count(distinct {c}) as sampled from {_tenth}), ({q.estimate('nb', c, _tenth, 256)})" for c in ("l_orderkey", "l_partkey", "l_linenumber")))


def builtin_errors(spark, d):
    """Whether the default hash and the engine's own counts are within five standard errors of the truth."""
    x = load(spark, d, "lineitem", ["l_orderkey", "l_linestatus"])
    ways = [estimators.estimate(x, "l_orderkey", SketchConfig(1024), k).select("method", "estimate", "rse") for k in MERGEABLE]
    ways += [estimators.estimate(x, "l_orderkey", SketchConfig(1024, layout="top"), "nb").select(F.lit("nb_top").alias("method"), "estimate", "rse")]
    for n, e, rse in (("approx_count_distinct", exact.builtin_approx(x, "l_orderkey"), 0.02), ("hll_sketch_agg", exact.builtin_hll(x, "l_orderkey"), 0.02), ("hll_union_agg", exact.builtin_union(x, "l_orderkey", "l_linestatus"), 0.02)):
        ways.append(e.select(F.lit(n).alias("method"), F.col("n").cast("double").alias("estimate"), F.lit(rse).alias("rse")))
    y = ways[0]
    for w in ways[1:]:
        y = y.union(w)
    n = exact.exact_distinct(x, "l_orderkey")
    return y.crossJoin(F.broadcast(n)).select("method", "n", (F.abs(F.col("estimate") / F.col("n") - 1) < 5 * F.col("rse")).alias("within"))


add("builtin_errors", builtin_errors, "select unnest(['nb', 'hll', 'loglog', 'pcsa', 'nb_top', 'approx_count_distinct', 'hll_sketch_agg', 'hll_union_agg']) as method, (select count(distinct l_orderkey) from lineitem) as n, true as within")


def embeddings_exact(spark, d):
    x = load(spark, d, "embeddings", ["embedding"])
    n = x.select("embedding").distinct().agg(F.count("*").alias("n"))
    return estimators.estimate(x, "embedding", SketchConfig(1024), "nb").crossJoin(F.broadcast(n)).select("n", (F.abs(F.col("estimate") / F.col("n") - 1) < 5 * F.col("rse")).alias("within"))


add("embeddings_exact", embeddings_exact, "select count(distinct embedding) as n, true as within from embeddings")


def nb_pow2(spark, d):
    """Cells from the first bits of the hash word."""
    return estimators.estimate(load(spark, d, "lineitem", ["l_orderkey", *FLAGS]), "l_orderkey", portable(256, layout="top"), "nb", FLAGS).select(*FLAGS, r6())


_pow2 = f"select {', '.join(FLAGS)}, bucket, bit_or(bit) as bitmap from ({q.hashed('l_orderkey', 'lineitem', 256, FLAGS, top=True)}) group by all"
add("nb_pow2", nb_pow2, f"select {', '.join(FLAGS)}, round({q.value('nb', 256)}, 6) as estimate from ({q.sums(_pow2, 256, FLAGS)})")


def nb_nulls_kept(spark, d):
    """Null as a value, and strings without case and outer spaces."""
    x = load(spark, d, "part", ["p_brand", "p_size", "p_type"]).select(F.when(F.col("p_size") > 25, F.col("p_brand")).alias("a"), F.when(F.col("p_size") % 3 != 0, F.concat(F.lit(" "), F.upper("p_type"))).alias("b"))
    cfg = portable(256, nulls="keep", strings="folded")
    return estimators.estimate(x, ["a", "b"], cfg, "nb").select(r6()).crossJoin(F.broadcast(estimators.estimate(x, ["a", "b"], portable(256), "nb").select(r6().alias("dropped"))))


_kept = "(select case when p_size > 25 then p_brand end as a, case when p_size % 3 <> 0 then ' ' || upper(p_type) end as b from part)"
_part = lambda c: f"coalesce(length(lower(trim({c}))) || ':' || lower(trim({c})), 'n')"
add("nb_nulls_kept", nb_nulls_kept, f"select estimate, dropped from ({q.estimate('nb', 'k', f'(select {_part(chr(97))} || {_part(chr(98))} as k from {_kept})', 256)}), (select estimate as dropped from ({q.estimate('nb', 'k', f'(select {q.composite(chr(97), chr(98))} as k from {_kept})', 256)}))")


def nb_segments(spark, d):
    """Overlapping segments of customers from one scan."""
    x = load(spark, d, "orders", ["o_custkey", "o_totalprice", "o_orderpriority", "o_orderstatus"])
    segments = {"all": F.lit(True), "dear": F.col("o_totalprice") > 200000, "urgent": F.col("o_orderpriority") == "1-URGENT", "open": F.col("o_orderstatus") == "O"}
    return estimators.from_sums(estimators.sums(registers.build_segments(x, "o_custkey", portable(256), segments), 256, ["segment"]), "nb", portable(256), ["segment"]).select("segment", r6())


add("nb_segments", nb_segments, "\nunion all\n".join(f"select '{n}' as segment, estimate from ({q.estimate('nb', 'o_custkey', f'(select o_custkey from orders where {w})', 256)})" for n, w in (("all", "true"), ("dear", "o_totalprice > 200000"), ("urgent", "o_orderpriority = '1-URGENT'"), ("open", "o_orderstatus = 'O'"))))


def nb_merge_sources(spark, d):
    """Sketches of each source's texts, merged, beside one of all."""
    x, cfg = load(spark, d, "documents", ["source", "text"]), portable(256)
    s = stored(registers.build(x, "text", cfg, ["source"]))
    one = estimators.from_sums(estimators.sums(registers.merge([s.drop("source")]), 256), "nb", cfg).select(F.lit("merged").alias("how"), r6())
    return one.union(estimators.estimate(x, "text", cfg, "nb").select(F.lit("one").alias("how"), r6()))


add("nb_merge_sources", nb_merge_sources, f"select unnest(['merged', 'one']) as how, estimate from ({q.estimate('nb', 'text', 'documents', 256)})")

# -- packed sketches ----------------------------------------------------------------------------


def _roundtrip(kind):
    def run(spark, d):
        """Packed at rest and unpacked: the cells again."""
        s = registers.build(load(spark, d, "lineitem", ["l_suppkey", "l_returnflag"]), "l_suppkey", portable(64), ["l_returnflag"])
        rows = s if kind == "pcsa" else registers.pairs(s, ["l_returnflag"])
        if kind.startswith("tc"):
            rows = tailcut.clamp(rows, 64, 4, ["l_returnflag"])
        x = codec.cells(codec.blobs(rows, 64, kind, ["l_returnflag"]), ["l_returnflag"])
        return x.select("l_returnflag", "bucket", *(["bitmap"] if kind == "pcsa" else codec.COLUMNS[kind]))
    return run


_s = q.cells("l_suppkey", "lineitem", 64, ["l_returnflag"])
_pr = f"select l_returnflag, cast(bucket as integer) as bucket, {q.TOP} as top, {q.NBR} as nbr from ({_s})"
_base = f"select l_returnflag, case when count(*) < 64 then 0 else min(top) end as base from ({_pr}) group by 1"
add("hll_roundtrip", _roundtrip("hll"), f"select l_returnflag, bucket, cast(top as tinyint) as top from ({_pr})")
add("pcsa_roundtrip", _roundtrip("pcsa"), f"select l_returnflag, cast(bucket as integer) as bucket, bitmap from ({_s})")
add("tc_hll_roundtrip", _roundtrip("tc_hll"), f"select l_returnflag, bucket, cast(least(top, base + 15) as tinyint) as top from ({_pr}) join ({_base}) using (l_returnflag)")
add("tc_nb_roundtrip", _roundtrip("tc_nb"), f"select l_returnflag, bucket, cast(least(top, base + 15) as tinyint) as top, cast(nbr as tinyint) as nbr from ({_pr}) join ({_base}) using (l_returnflag)")


def packed_sizes(spark, d):
    """Bytes at rest of each kind, as written."""
    s, out = stored(registers.build(load(spark, d, "lineitem", ["l_orderkey"]), "l_orderkey", portable(256))), None
    for kind in codec.WIDTHS:
        rows = s if kind == "pcsa" else registers.pairs(s)
        rows = tailcut.clamp(rows, 256) if kind.startswith("tc") else rows
        e = codec.blobs(rows, 256, kind).select("kind", "m", F.octet_length("payload").cast("int").alias("n_bytes"))
        out = e if out is None else out.union(e)
    return out


add("packed_sizes", packed_sizes, "\nunion all\n".join(f"select '{k}' as kind, 256 as m, {v} as n_bytes" for k, v in (("hll", "256 * 6 // 8"), ("nb", "256 * 7 // 8"), ("pcsa", "256 * 8"), ("tc_hll", "256 * 4 // 8 + 1"), ("tc_nb", "256 * 5 // 8 + 1"))))


def _stored_blobs(spark, d):
    register_blobs(spark)
    p = registers.pairs(registers.build(load(spark, d, "orders", ["o_custkey", "o_orderpriority"]), "o_custkey", portable(256), ["o_orderpriority"]), ["o_orderpriority"])
    stored(codec.blobs(p, 256, "nb", ["o_orderpriority"])).createOrReplaceTempView("stored_sketches")


def blob_card(spark, d):
    _stored_blobs(spark, d)
    return spark.sql("select o_orderpriority, round(nb_card(payload, m), 6) as estimate from stored_sketches")


def blob_merge(spark, d):
    _stored_blobs(spark, d)
    return spark.sql("with u as (select nb_merge(payload, m) as payload from stored_sketches) select round(nb_card(payload, 256), 6) as estimate from u")


def blob_explain(spark, d):
    _stored_blobs(spark, d)
    return spark.sql("select s.o_orderpriority, e.bucket, e.top, e.nbr from stored_sketches s, lateral nb_explain(s.payload, s.m) e")


add("blob_card", blob_card, q.estimate("nb", "o_custkey", "orders", 256, ["o_orderpriority"]))
add("blob_merge", blob_merge, q.estimate("nb", "o_custkey", "orders", 256))
add("blob_explain", blob_explain, f"select o_orderpriority, cast(bucket as integer) as bucket, cast({q.TOP} as integer) as top, cast({q.NBR} as integer) as nbr from ({q.cells('o_custkey', 'orders', 256, ['o_orderpriority'])})")

# -- streams ------------------------------------------------------------------------------------
EVENTS = ["event_id", "ts", "user_id", "event_type"]


def _windowed(size, slide=None):
    def run(spark, d):
        cfg = portable(64)
        s = windows.with_event_time(windows.event_stream(spark, d))
        cells = windows.drain(windows.windowed(s, "user_id", cfg, size, slide, ["event_type"]))
        return windows.window_estimates(cells, cfg, "nb", ["event_type"]).select(F.date_format("start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", r6())
    return run


_start = "strftime(cast(ts as date), '%Y-%m-%d %H:%M')"
_daily = q.estimate("nb", "user_id", f"(select {_start} as start, event_type, user_id from events)", 64, ["start", "event_type"])
add("stream_tumbling", _windowed("1 day"), _daily)
_slid = "(select strftime(unnest([cast(ts as date), cast(ts as date) - interval 1 day]), '%Y-%m-%d %H:%M') as start, event_type, user_id from events)"
add("stream_sliding", _windowed("2 days", "1 day"), q.estimate("nb", "user_id", _slid, 64, ["start", "event_type"]))


def _batches(spark, d, batches, late=False):
    """The events as a stream of files, ranges of event_id.  With late, an event of the first day comes again in a last file,
    weeks behind the watermark."""
    x, path = load(spark, d, "events", EVENTS), scratch(spark)
    windows.as_files(x, "event_id", batches, path)
    if late:
        x.where("event_id < 20").withColumn("user_id", F.col("user_id") + 1_000_000).coalesce(1).write.parquet(f"{path}/part=late")
    return windows.file_stream(spark, path, x.schema), path


def stream_batches(spark, d):
    """Six batches: daily windows that the watermark closes, and after them those still open, equal one batch over all.  The
    stream stops after its first batches and goes on from its checkpoint; an event that comes too late counts nowhere."""
    cfg = portable(64)
    stream, path = _batches(spark, d, 6, late=True)
    out, checkpoint = scratch(spark), scratch(spark)
    cells = lambda s: windows.windowed(windows.with_event_time(s, "1 day"), "user_id", cfg, "1 day", None, ["event_type"])
    some = windows.file_stream(spark, path, stream.schema, files=2)
    q1 = cells(some).writeStream.outputMode("append").option("checkpointLocation", checkpoint).foreachBatch(lambda b, i: b.write.mode("overwrite").parquet(f"{out}/batch={i}")).start()
    q1.processAllAvailable()
    q1.stop()
    x = windows.drain(cells(stream), "append", out, checkpoint)
    last = load(spark, d, "events", ["ts"]).agg(F.date_trunc("day", F.max("ts")).alias("z"))
    closed = x.join(F.broadcast(last), F.col("start") < F.col("z").cast("timestamp") - F.expr("interval 1 day")).drop("z")
    return windows.window_estimates(closed, cfg, "nb", ["event_type"]).select(F.date_format("start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", r6())


add("stream_batches", stream_batches, f"select * from ({_daily}) where start < (select strftime(cast(max(ts) as date) - interval 1 day, '%Y-%m-%d %H:%M') from events)")


def stream_stateful(spark, d):
    """A sequential sketch a type, fed by a stream of four batches; the last update of each group."""
    s, _ = _batches(spark, d, 4)
    x = windows.drain(windows.stateful_martingale(s, "user_id", "event_type", "event_id", portable(64)), "update")
    return x.groupBy("event_type").agg(F.max("rows_in").alias("rows_in"), F.round(F.max_by("est", "rows_in"), 6).alias("est"), F.round(F.max_by("var", "rows_in"), 4).alias("var"))


_mart = q.martingale("nb", "user_id", "events", ["event_id"], 64, ["event_type"])
add("stream_stateful", stream_stateful, f"select event_type, n as rows_in, est, var from ({_mart}) join (select event_type, count(*) as n from events group by all) using (event_type)")


def stream_processor(spark, d):
    """The same by a stateful processor over RocksDB."""
    s, _ = _batches(spark, d, 4)
    x = windows.drain(windows.transformed_martingale(s, "user_id", "event_type", "event_id", portable(64)), "update", conf=windows.ROCKSDB)
    return x.groupBy("event_type").agg(F.max("rows_in").alias("rows_in"), F.round(F.max_by("est", "rows_in"), 6).alias("est"), F.round(F.max_by("var", "rows_in"), 4).alias("var"))


add("stream_processor", stream_processor, f"select event_type, n as rows_in, est, var from ({_mart}) join (select event_type, count(*) as n from events group by all) using (event_type)")


def stream_first_seen(spark, d):
    """The same without Python on rows: first arrivals, merged batch by batch."""
    s, _ = _batches(spark, d, 4)
    f = windows.FirstSeen(spark, scratch(spark), portable(64), ["event_type"])
    f.run(s, "user_id", "event_id", scratch(spark))
    return f.estimates().select("event_type", "changes", F.round("est", 6).alias("est"), F.round("var", 4).alias("var"))


add("stream_first_seen", stream_first_seen, f"select event_type, changes, est, var from ({_mart})")


def stream_exact(spark, d):
    """New users within the watermark, of a stream of one day's batch: all distinct users of the table if the delay spans it."""
    x = windows.drain(windows.exact_stream(windows.event_stream(spark, d), "user_id", "60 days").select("user_id"), "append")
    return x.agg(F.count("*").alias("n"))


add("stream_exact", stream_exact, "select count(distinct user_id) as n from events")


def stream_enriched(spark, d):
    """Events joined with customers' nations, distinct users by nation."""
    c = load(spark, d, "customer", ["c_custkey", "c_nationkey"]).withColumnRenamed("c_custkey", "user_id")
    x = windows.drain(windows.enriched(windows.event_stream(spark, d).select("user_id"), c, "user_id"), "append")
    return estimators.estimate(x, "user_id", portable(64), "nb", ["c_nationkey"]).select("c_nationkey", r6())


add("stream_enriched", stream_enriched, q.estimate("nb", "user_id", "(select user_id, c_nationkey from events join customer on user_id = c_custkey)", 64, ["c_nationkey"]))


def stream_followed(spark, d):
    """Users with a purchase within a day after a click: a join of two streams, counted."""
    s = lambda kind: windows.event_stream(spark, d).where(F.col("event_type") == kind).select(*EVENTS[:3])
    x = windows.drain(windows.followed(s("click"), s("purchase"), "user_id", "1 day", "60 days"), "append")
    e = estimators.estimate(x, "user_id", portable(64), "nb").select(r6())
    return x.agg(F.count("*").alias("pairs")).crossJoin(F.broadcast(e))


_pairs = "(select a.user_id from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 1 day)"
add("stream_followed", stream_followed, f"select pairs, estimate from (select count(*) as pairs from {_pairs}), ({q.estimate('nb', 'user_id', _pairs, 64)})")


def stream_sessions(spark, d):
    x = load(spark, d, "events", ["ts", "user_id"]).withColumn("ts", F.col("ts").cast("timestamp"))
    return windows.sessions(x, "user_id", "6 hours").groupBy("user_id").agg(F.count("*").alias("n_sessions"), F.max("n_rows").alias("longest"))


add("stream_sessions", stream_sessions, """with g as (select user_id, ts, case when ts - lag(ts) over w < interval 6 hour then 0 else 1 end as fresh from events window w as (partition by user_id order by ts)),
s as (select user_id, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as s from g), c as (select user_id, s, count(*) as n from s group by all)
select user_id, count(*) as n_sessions, max(n) as longest from c group by user_id""")


def session_users(spark, d):
    """Distinct users inside each session of a type: sessions of a stream end after ten quiet minutes."""
    s = windows.with_event_time(windows.event_stream(spark, d), "1 hour")
    cells = windows.drain(windows.session_sketches(s, "user_id", "event_type", "10 minutes", portable(16)), "complete")
    keys = ["event_type", "start"]
    e = estimators.from_sums(estimators.sums(cells, 16, keys), "nb", portable(16), keys)
    return e.select("event_type", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), r6())


_ses = """(with g as (select event_type, user_id, ts, case when ts - lag(ts) over w < interval 10 minute then 0 else 1 end as fresh from events window w as (partition by event_type order by ts)),
s as (select *, sum(fresh) over (partition by event_type order by ts rows unbounded preceding) as s from g) select event_type, user_id, strftime(min(ts) over (partition by event_type, s), '%Y-%m-%d %H:%M:%S') as start from s)"""
add("session_users", session_users, q.estimate("nb", "user_id", _ses, 16, ["event_type", "start"]))
