"""Every query that has a SQL twin gives its rows; the others give some."""

import glob
import os

import duckdb
import pytest

from cardsketch.plans import experiments, queries as base, relational  # noqa: F401


@pytest.fixture(scope="module")
def duck(sf_dir):
    con = duckdb.connect()
    for f in glob.glob(f"{sf_dir}/*.parquet"):
        con.execute(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    return con


@pytest.mark.parametrize("name", list(base.QUERIES))
def test_query(spark, sf_dir, duck, name):
    df = base.QUERIES[name](spark, sf_dir)
    cols = sorted(df.columns)
    got = sorted(str(tuple(r[c] for c in cols)) for r in df.collect())
    assert got
    if name in base.ORACLES:
        r = duck.execute(base.ORACLES[name])
        names = [c[0] for c in r.description]
        assert sorted(names) == cols
        assert got == sorted(str(tuple(x[names.index(c)] for c in cols)) for x in r.fetchall())


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
    assert set(base.QUERIES) <= set(__spark_entry__.queries())
