"""Where queries and their SQL twins are registered by name."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import load

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
#: Sketches of 16 cells a unit of a line's quantity: (m, lines) for each that occurs.
SIZES_SQL = "(select cast(floor(l_quantity * 16) as integer) as m, count(*) as lines from lineitem where l_quantity >= 1 group by 1)"
FLAGS = ["l_returnflag", "l_linestatus"]


def add(name: str, run: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        ORACLES[name] = sql


def r6(c: str = "estimate", digits: int = 6):
    return F.round(c, digits).alias(c)


def sizes(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "lineitem", ["l_quantity"]).where("l_quantity >= 1").groupBy(F.floor(F.col("l_quantity") * 16).cast("int").alias("m")).agg(F.count("*").alias("lines"))


def each(x: DataFrame, rows: Callable[..., list[tuple]], schema: str) -> DataFrame:
    """The rows that a function makes of each row's values."""
    names = [c.split()[0] for c in schema.split(", ")]

    def run(batches):
        for pdf in batches:
            yield pd.DataFrame([y for r in pdf.itertuples(index=False) for y in rows(*r)], columns=names)

    return x.mapInPandas(run, schema)
