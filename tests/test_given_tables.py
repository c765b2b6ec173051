"""Queries of laws and measures read the given tables: what they count doubles when a table does."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from cardsketch.operators import entropy
from cardsketch.plans import experiments, queries as base  # noqa: F401

COUNTS = {
    "constants_table": "lines",
    "pair_law": "orders",
    "integrand_forms": "lines",
    "mean_error": "lines",
    "memory_bits": "lines",
    "mvp_table1": "lines",
    "memory_ratios": "n",
    "mvp_measured": "runs",
    "retrospective_variance": "runs",
    "order_sensitivity": "runs",
    "ablation_width": "runs",
}


@pytest.fixture(scope="module")
def doubled(spark, sf_dir, tmp_path_factory):
    d = tmp_path_factory.mktemp("doubled")
    for name in ("lineitem",):
        x = spark.read.parquet(f"{sf_dir}/{name}.parquet")
        more = {c: (F.col(c) + 10_000_000).cast(x.schema[c].dataType) for c in x.columns if c in ("l_orderkey", "l_suppkey")}
        x.union(x.withColumns(more)).write.parquet(f"{d}/{name}.parquet")
    return str(d)


@pytest.mark.parametrize("name", list(COUNTS))
def test_counts_follow_the_table(spark, sf_dir, doubled, name):
    of = lambda d: sorted((r[COUNTS[name]] for r in base.QUERIES[name](spark, d).collect()))
    once = of(sf_dir)
    assert once and of(doubled) == [2 * n for n in once]


def test_all_likelihoods_at_once():
    rng, m, n = np.random.default_rng(2), 32, 600
    s = rng.binomial(m, -np.expm1(-n / (m * 2.0 ** np.arange(1, 45))), (50, 44))
    s[7] = 0
    e, b = entropy.solve_all(s, m)
    want = [entropy.solve(dict(enumerate(map(int, x), 1)), m) for x in s]
    assert np.allclose(e, [x for x, _ in want], rtol=1e-6) and np.allclose(b, [x for _, x in want], rtol=1e-9)


def test_errors_stay_under_the_stated_bound(spark, sf_dir):
    rows = base.QUERIES["mean_error"](spark, sf_dir).collect()
    assert rows and all(abs(r["error"]) <= r["bound"] for r in rows)
