"""Sketch laws, accuracy, sequential and lossy variants, theory and plans."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from cardsketch.config import SketchConfig, portable
from cardsketch.functions import constants, sqlfuncs, theory
from cardsketch.operators import codec, entropy, estimators, exact, martingale, measures, registers, setops, tailcut
from cardsketch.plans import planner
from cardsketch.sources import simulate
from cardsketch.sources.tables import load

HAND = [([], 0, 1, 0), ([1], 1, 1, 1), ([2], 2, 0, 0), ([2, 1], 2, 1, 2), ([1, 2], 2, 1, 2), ([3, 1], 3, 0, 1), ([3, 2], 3, 1, 0), ([1, 3, 2], 3, 1, 3), ([5, 5, 5], 5, 0, 0), ([4, 5], 5, 1, 0), ([5, 4], 5, 1, 0), ([2, 5, 3], 5, 0, 0)]


def from_ranks(spark, rows):
    """(case, bucket, bitmap) from lists of ranks."""
    x = [(i, j, 1 << (k - 1)) for i, cells in enumerate(rows) for j, ks in enumerate(cells) for k in ks]
    return spark.createDataFrame(x, "case int, bucket int, bit long").groupBy("case", "bucket").agg(F.bit_or("bit").alias("bitmap"))


def test_hand_cases(spark):
    s = from_ranks(spark, [[h[0]] for h in HAND])
    got = {r["case"]: (r["top"], r["nbr"]) for r in registers.pairs(s, ["case"]).collect()}
    gaps = {r["case"]: r["g"] for r in s.select("case", registers.gap_of(F.col("bitmap")).alias("g")).collect()}
    for i, (ks, top, nbr, gap) in enumerate(HAND):
        state = (0, 1)
        for k in ks:
            state = registers.nb_update(*state, k)
        assert state == (top, nbr)
        if ks:
            assert got[i] == (top, nbr) and gaps[i] == gap


def test_updates_one_by_one_equal_the_fold(spark):
    rng = np.random.default_rng(1)
    rows = [[[int(k) for k in np.minimum(rng.geometric(0.5, rng.integers(0, 12)), 20)] for _ in range(3)] for _ in range(200)]
    got = {(r["case"], r["bucket"]): (r["top"], r["nbr"]) for r in registers.pairs(from_ranks(spark, rows), ["case"]).collect()}
    for i, cells in enumerate(rows):
        for j, ks in enumerate(cells):
            for order in (ks, ks[::-1], ks + ks):
                state = (0, 1)
                for k in order:
                    state = registers.nb_update(*state, k)
                assert state == got.get((i, j), (0, 1))


def test_merge_laws(spark):
    pairs = [(t, n) for t in range(7) for n in (0, 1) if not (t <= 1 and n == 0)]
    rows = [(i, a, b, c, d) for i, ((a, b), (c, d)) in enumerate((x, y) for x in pairs for y in pairs)]
    x = spark.createDataFrame(rows, "case int, at int, an int, bt int, bn int")
    side = lambda t, n: x.where(f"{t} > 0").select("case", F.lit(0).alias("bucket"), F.col(t).alias("top"), F.col(n).alias("nbr"))
    got = {r["case"]: (r["top"], r["nbr"]) for r in registers.merge_pairs([side("at", "an"), side("bt", "bn")], ["case"]).collect()}
    for i, a, b, c, d in rows:
        want = (a, b | d) if a == c else ((a, 1 if a - c == 1 and c > 0 else b) if a > c else (c, 1 if c - a == 1 and a > 0 else d))
        assert got.get(i, (0, 1)) == want


def test_nulls_duplicates_and_empty_input(spark):
    cfg = SketchConfig(64)
    x = spark.createDataFrame([(1, "a"), (None, "b"), (2, None), (1, "a")], "n int, s string")
    est = lambda df, c: estimators.estimate(df, c, cfg).first()
    assert abs(est(x, "n")["estimate"] - 2) < 0.1 and abs(est(x, ["n", "s"])["estimate"] - 1) < 0.1
    e = est(x.where("n > 5"), "n")
    assert e["estimate"] == 0 and e["regime"] == "empty"
    assert estimators.estimate(x.where("n is null"), "n", cfg).first()["estimate"] == 0
    assert estimators.estimate(x.where("n > 5"), "n", cfg, by=["s"]).count() == 0
    y = spark.createDataFrame([({"a": 1, "b": 2}, 0.0), ({"b": 2, "a": 1}, -0.0)], "m map<string,int>, z double")
    assert abs(est(y, "m")["estimate"] - 1) < 0.1 and abs(est(y, "z")["estimate"] - 1) < 0.1


@pytest.mark.parametrize("family", ["xxhash64", "md5"])
@pytest.mark.parametrize("kind", ["nb", "hll", "loglog", "pcsa"])
def test_accuracy(spark, family, kind):
    x, n = spark.range(40_000), 40_000
    m = 1195
    e = estimators.estimate(x, "id", SketchConfig(m, family), kind).first()
    assert abs(e["estimate"] / n - 1) < 4 * e["rse"] and e["lo"] < e["estimate"] < e["hi"]


def test_bitmap_is_within_a_few_binary_orders(spark):
    e = estimators.bitmap_estimate(spark.range(40_000), "id", SketchConfig(1)).first()["estimate"]
    assert 40_000 / 16 < e < 40_000 * 16


def test_constants():
    golden = {16: (0.915524, 0.917297, 0.8444, 0.673102, 1.2237), 64: (0.950157, 0.950272, 0.7920, 0.709208, 1.1120), 256: (0.958882, 0.958889, 0.7801, 0.718308, 1.0874), 1024: (0.961068, 0.961068, 0.7772, 0.720587, 1.0814), 16384: (0.961751, 0.961751, 0.7762, 0.721300, 1.0796)}
    for m, (g, lap, b, a, h) in golden.items():
        assert abs(constants.gamma(m) - g) < 2e-6 and abs(constants.gamma(m, "laplace") - lap) < 2e-6 and abs(constants.alpha(m) - a) < 2e-6
        assert abs(constants.variance("nb", m) - b) < 1e-4 and abs(constants.variance("hll", m) - h) < 1e-4
    assert abs(constants.gamma(1, "limit") - 0.962) < 1e-3 and abs(constants.variance("nb", None) - 0.776) < 1e-3
    assert abs(constants.martingale_variance("nb") - 0.52) < 1e-3 and abs(constants.martingale_variance("hll") - 0.693) < 1e-3


def test_theory():
    assert theory.bounds_hold(np.concatenate((np.linspace(0.01, 1, 200), np.linspace(1, 50, 200))))
    for a, b in ((1, 2), (2.5, 7), (3, 4)):
        assert abs(theory.harmonic_sum(a, b) - math.log2(b / a)) < 1e-4
    for kind, f in (("nb", constants.f_nb), ("hll", constants.f_hll)):
        for u in (0.1, 1.0, 3.0):
            assert abs(theory.poisson_cell(kind, 1e4, u) - f(u)) < 1e-4
    assert abs(sum(theory.p_pair(k, s, 5) for k in range(60) for s in (0, 1)) - 1) < 1e-9
    rng = np.random.default_rng(2)
    for kind in ("nb", "hll"):
        want = theory.exact_moment(kind, 2, 3)
        got = []
        for _ in range(20000):
            states = [(0, 1), (0, 1)]
            for c, k in zip(rng.integers(0, 2, 3), rng.geometric(0.5, 3)):
                states[c] = registers.nb_update(*states[c], int(k))
            got.append(1 / sum(2.0**-t * ((3 - 2 * n) if kind == "nb" else 1) for t, n in states))
        assert abs(np.mean(got) - want) < 5 * np.std(got) / len(got) ** 0.5
    m, lam = 64, 64e3
    mean, var = theory.poisson_mean("nb", m, lam), theory.poisson_variance("nb", m, lam)
    assert abs(constants.gamma(m) * m * m * mean / lam - 1) < 2e-3
    assert abs(m * var / mean**2 / constants.variance("nb", m) - 1) < 0.02
    assert abs(theory.martingale_relative_variance("nb", 64, 10**6) * 64 - 1 / (2 * constants.gamma(64))) < 0.01


def test_measures(spark):
    for k, published in (("nb", 5.46), ("hll", 6.48), ("loglog", 10.11), ("pcsa", 38.9), ("entropy", 1.98)):
        assert abs(measures.mvp(k) - published) < 0.05
    for (a, b), ratio in {("nb", "hll"): 0.837, ("mart_nb", "mart_hll"): 0.88, ("tc_nb", "tc_hll"): 0.896}.items():
        assert abs(measures.memory_ratio(a, b) - ratio) < 0.006
    e = spark.createDataFrame([(9.0, 10.0, 8.0, 11.0), (12.0, 10.0, 11.0, 13.0)], "estimate double, n double, lo double, hi double")
    a = measures.accuracy(e, "n").first()
    assert abs(a["bias"] - 0.05) < 1e-9 and abs(a["rel_mse"] - 0.025) < 1e-9 and measures.coverage(e, "n").first()[0] == 0.5


def sequential_fold(rows, m, kind):
    state, total, est, var, changes = {}, float(m), 0.0, 0.0, 0
    for cell, k in rows:
        a = state.get(cell, (0, 1))
        b = registers.nb_update(*a, k)
        term = lambda s: 2.0 ** -s[0] * ((3 - 2 * s[1]) if kind == "nb" else 1)
        if term(a) != term(b):
            q = total / m
            est, var, changes, total = est + 1 / q, var + (1 - q) / q**2, changes + 1, total + term(b) - term(a)
        state[cell] = b
    return changes, est, var


@pytest.mark.parametrize("kind", ["nb", "hll"])
def test_martingale_equals_a_plain_fold(spark, sf_dir, kind):
    from cardsketch.functions.hashing import split

    x, cfg = load(spark, sf_dir, "orders"), portable(64)
    rows = split(x, "o_custkey", cfg, keep=[F.col("o_orderdate"), F.col("o_orderkey")]).orderBy("o_orderdate", "o_orderkey").collect()
    want = sequential_fold([(r["bucket"], r["bit"].bit_length()) for r in rows], 64, kind)
    got = martingale.martingale(x, "o_custkey", ["o_orderdate", "o_orderkey"], cfg, kind).first()
    assert got["changes"] == want[0] and abs(got["est"] - want[1]) < 1e-6 and abs(got["var"] - want[2]) < 1e-4


def test_golden_martingale(spark, sf_dir):
    x = load(spark, sf_dir.replace("sf0.001", "sf0.01"), "orders")
    r = martingale.martingale(x, "o_custkey", ["o_orderdate", "o_orderkey"], portable(64)).first()
    assert r["changes"] == 233 and abs(r["est"] - 1744.492497) < 1e-5 and abs(r["var"] - 24665.784869) < 1e-3


def test_sequential_states_do_not_merge(spark):
    t = spark.createDataFrame([(0, 1.0, 1.0)], "bucket int, est double, q_before double")
    with pytest.raises(ValueError):
        registers.merge([t, t])


def test_tail_cut(spark, sf_dir):
    x, cfg = load(spark, sf_dir, "orders"), portable(16)
    order = ["o_orderdate", "o_orderkey"]
    from cardsketch.functions.hashing import split

    rows = split(x, "o_orderkey", cfg, keep=[F.col(c) for c in order]).orderBy(*order).collect()
    for width in (2, 4):
        t = tailcut.TailCut(16, width)
        for r in rows:
            t.add(r["bucket"], r["bit"].bit_length())
        got = {r["bucket"]: (r["top"], r["nbr"]) for r in tailcut.sequential(x, "o_orderkey", order, cfg, "nb", width).collect()}
        assert got == {i: (int(a), int(b)) for i, (a, b) in enumerate(zip(t.tops(), t.nbr))}
    lossless = {r["bucket"]: (r["top"], r["nbr"]) for r in registers.pairs(registers.build(x, "o_orderkey", cfg)).collect()}
    assert {k: v[0] for k, v in got.items()} == {k: v[0] for k, v in lossless.items()}  # nothing was cut
    # one far element first, or last: the order decides
    a, b = tailcut.TailCut(2, 4), tailcut.TailCut(2, 4)
    far, fill = [(0, 30)], [(c, k) for k in range(1, 14) for c in (0, 1)]
    for c, k in far + fill:
        a.add(c, k)
    for c, k in fill + far:
        b.add(c, k)
    assert a.tops().tolist() != b.tops().tolist()
    top = np.maximum(a.tops(), b.tops())
    assert a.merged(b).tops().tolist() == np.minimum(top, top.min() + 15).tolist()


def test_codec(spark, sf_dir):
    rng = np.random.default_rng(3)
    for kind, cols in (("nb", [rng.integers(0, 61, 100), rng.integers(0, 2, 100)]), ("hll", [rng.integers(0, 61, 100)]), ("pcsa", [rng.integers(0, 1 << 60, 100)])):
        b = codec.pack_cells(kind, cols)
        assert len(b) == -(-100 * sum(codec.WIDTHS[kind]) // 8)
        assert all((u == c).all() for u, c in zip(codec.unpack_cells(kind, b, 100), cols))


def test_set_sizes(spark):
    cfg = SketchConfig(2048)
    a, b = registers.build(spark.range(0, 30000), "id", cfg), registers.build(spark.range(20000, 50000), "id", cfg)
    r = setops.set_sizes(a, b, cfg).first()
    assert abs(r["n_union"] / 50000 - 1) < 0.08 and abs(r["n_both"] - 10000) < 4000 and abs(r["n_only_a"] - 20000) < 4000


def test_entropy_is_the_most_accurate(spark):
    s = registers.build(spark.range(50_000), "id", SketchConfig(512))
    est, bits = entropy.entropy_estimate(s, 512)
    assert abs(est / 50_000 - 1) < 4 * (0.42 / 512) ** 0.5 + 0.01 and 4 < bits / 512 < 5.5
    assert entropy.solve({1: 0, 2: 0}, 8) == (0.0, 0.0)


@pytest.mark.parametrize("which,better,worse", [("a", "nb", "hll"), ("b", "mart_nb", "mart_hll"), ("c", "tc_nb", "tc_hll")])
def test_equal_memory_order(spark, which, better, worse):
    rows = simulate.plot_errors(spark, which, streams=6000, cells=64, n=2e4, checkpoints=1).collect()
    mse = {r["method"]: r["rel_mse"] for r in rows}
    assert mse[better] < mse[worse]
    m_mse = {r["method"]: r["m_mse"] for r in rows}
    theory_ = {"nb": 0.792, "hll": 1.11, "mart_nb": 0.52, "mart_hll": 0.69, "tc_nb": 0.792, "tc_hll": 1.11}
    for k, v in m_mse.items():
        assert abs(v / theory_[k] - 1) < 0.12


def test_sql_functions(spark):
    sqlfuncs.register(spark)
    spark.range(20_000).createOrReplaceTempView("ids")
    got = spark.sql(sqlfuncs.distinct_sql("ids", "id", 1024)).first()[0]
    want = estimators.estimate(spark.range(20_000), "id", SketchConfig(1024)).first()["estimate"]
    assert abs(got - want) < 1e-6


def test_store_and_cube(spark, sf_dir, tmp_path):
    x, cfg = load(spark, sf_dir, "events"), SketchConfig(128)
    store = planner.SketchStore(spark, str(tmp_path / "s"), cfg, ["event_type"])
    store.write(x, "user_id", F.col("ts"))
    got = store.answer("2024-01-03", "2024-01-10").first()["estimate"]
    want = estimators.estimate(x.where("to_date(ts) between '2024-01-03' and '2024-01-10'"), "user_id", cfg).first()["estimate"]
    assert got == want
    assert planner.join_size(10, 20, 100, 40) == 200


def test_exact(spark, sf_dir):
    x = load(spark, sf_dir, "lineitem")
    n = exact.exact_distinct(x, "l_partkey").first()[0]
    for e in (exact.builtin_approx(x, "l_partkey"), exact.builtin_hll(x, "l_partkey")):
        assert abs(e.first()[0] / n - 1) < 0.1


def test_plan_is_native_and_pruned(spark, sf_dir):
    e = estimators.estimate(spark.read.parquet(f"{sf_dir}/lineitem.parquet"), "l_orderkey", SketchConfig(256), by=["l_returnflag"])
    plan = e._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and plan.count("Exchange") <= 3 and "partial_bit_or" in plan
    assert "IsNotNull(l_orderkey)" in plan and "l_comment" not in plan
    schema = plan[plan.index("ReadSchema"):].split("\n")[0]
    assert "l_orderkey" in schema and "l_returnflag" in schema and "l_tax" not in schema


def test_laws_as_printed_and_true():
    assert theory.p_pair(2, 0, 1) == 0.25 and theory.p_pair_printed(2, 0, 1) == 0.125
    assert abs(theory.p_pair(3, 0, 400) - theory.p_pair_printed(3, 0, 400)) < 1e-12
    assert abs(theory.integrand(10, 1, "printed") - constants.f_nb(1)) > 1e-3 > 1e-5 > abs(theory.integrand(10, 1) - constants.f_nb(1))
    assert all(abs(theory.mean_error(m)) <= 8.4e-5 for m in (16, 64, 256, 1024))


def test_elements(spark):
    """Composite elements are told apart, nulls kept if asked for, strings folded if asked for."""
    x = spark.createDataFrame([("a|b", "c"), ("a", "b|c"), (" A|B ", "C"), (None, "c"), ("c", None), (None, None)], "x string, y string")
    for family in ("md5", "xxhash64"):
        n = lambda **kw: round(estimators.estimate(x, ["x", "y"], SketchConfig(64, family, **kw)).first()["estimate"])  # noqa: B023, E731
        assert (n(), n(strings="folded"), n(nulls="keep"), n(nulls="keep", strings="folded")) == (3, 2, 6, 5)
    y = spark.createDataFrame([(float("nan"),), (-float("nan"),), (0.0,), (-0.0,)], "z double")
    assert round(estimators.estimate(y, "z", SketchConfig(64)).first()["estimate"]) == 2


@pytest.mark.parametrize("m", [1, 2, 64, 1024])
def test_cells_from_the_first_bits(spark, m):
    x = spark.range(30_000)
    for family in ("md5", "xxhash64"):
        s = registers.build(x, "id", SketchConfig(m, family, layout="top"))
        assert s.count() == m and s.where(f"bucket < 0 or bucket >= {m}").count() == 0
        if m == 1024:
            e = estimators.from_sums(estimators.sums(s, m), "nb", SketchConfig(m)).first()
            assert abs(e["estimate"] / 30_000 - 1) < 5 * e["rse"]
    with pytest.raises(ValueError):
        SketchConfig(1195, layout="top")


def test_renamed_sequential_states_do_not_merge(spark, sf_dir):
    t = martingale.martingale(load(spark, sf_dir, "orders"), "o_custkey", ["o_orderkey"], portable(16)).withColumnsRenamed({"est": "a", "var": "b"})
    with pytest.raises(ValueError):
        registers.merge([t, t])


def test_packed_tail_cut():
    rng = np.random.default_rng(4)
    top, nbr = rng.integers(3, 19, 100), rng.integers(0, 2, 100)
    top[0] = 3
    for kind, cols in (("tc_nb", [top, nbr]), ("tc_hll", [top])):
        b = codec.pack_cells(kind, cols)
        assert len(b) == codec.payload_bytes(kind, 100) and all((u == c).all() for u, c in zip(codec.unpack_cells(kind, b, 100), cols))


def test_tail_cut_simulation_equals_a_replay():
    for seed in range(60):
        rng = np.random.default_rng(seed)
        m, n = 4, int(rng.integers(5, 3000))
        cell, k = rng.integers(0, m, n), rng.geometric(0.5, n) + (rng.random(n) < 0.01) * 14
        t = tailcut.TailCut(m)
        for c, r in zip(cell.tolist(), k.tolist()):
            t.add(c, r)
        first = np.full((m, 15), np.inf)
        for i, (c, r) in enumerate(zip(cell, k)):
            if r <= 15:
                first[c, r - 1] = min(first[c, r - 1], i)
        far = k > 15
        top, nbr = simulate.tail_cut_cells(first, (np.flatnonzero(far).astype(float), cell[far], k[far]), float(n), 15)
        assert (top == t.tops()).all() and (nbr == t.nbr).all()


@pytest.mark.parametrize("which,published", [("a", 0.837), ("b", 0.88), ("c", 0.896)])
def test_ratio_of_errors(spark, which, published):
    """At equal memory the ratio of errors is that of memory at equal errors."""
    r = simulate.plot_ratio(spark, which, streams=4000, cells=256, n=1e5, checkpoints=1).first()
    assert abs(r["ratio"] - published) < 3 * r["ratio_se"] + 0.01 and r["ratio"] + 2 * r["ratio_se"] < 1.02
    assert abs(r["predicted"] - published) < 0.01


def test_measured_products(spark):
    for r in simulate.measured_products(spark, streams=1500, m=128, n=1e5).collect():
        assert abs(r["measured"] / r["published"] - 1) < 0.2, r


def test_own_variances(spark):
    for r in simulate.own_variances(spark, streams=1500).collect():
        assert abs(r["own"] / r["true"] - 1) < 0.15


def test_order_matters_to_short_offsets_only(spark):
    r = {x["width"]: x for x in simulate.order_share(spark, streams=40, n=5000).collect()}
    assert r[2]["by_order"] > 0.3 and r[2]["by_merge"] > 0.3 and r[4]["by_order"] < 0.1 and r[4]["by_merge"] < 0.1
