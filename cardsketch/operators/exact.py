"""Exact counts and the engine's own approximate ones, to compare with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _cols(cols: str | list[str]) -> list[str]:
    return [cols] if isinstance(cols, str) else list(cols)


def exact_distinct(df: DataFrame, cols: str | list[str], by: list[str] = ()) -> DataFrame:
    return df.groupBy(*by).agg(F.countDistinct(*_cols(cols)).alias("n"))


def builtin_approx(df: DataFrame, col: str, by: list[str] = (), rsd: float = 0.02) -> DataFrame:
    return df.groupBy(*by).agg(F.approx_count_distinct(col, rsd).alias("n"))


def builtin_hll(df: DataFrame, col: str, by: list[str] = (), lg: int = 12) -> DataFrame:
    return df.groupBy(*by).agg(F.hll_sketch_estimate(F.hll_sketch_agg(col, lg)).alias("n"))


def builtin_union(df: DataFrame, col: str, shard: str, lg: int = 12) -> DataFrame:
    """The engine's sketches of each shard, merged."""
    s = df.groupBy(shard).agg(F.hll_sketch_agg(col, lg).alias("sketch"))
    return s.agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("n"))


def exact_many(df: DataFrame, cols: list[str], by: list[str] = ()) -> DataFrame:
    """Several exact counts at once, for which the engine makes a copy of each row by column."""
    return df.groupBy(*by).agg(*[F.countDistinct(c).alias(f"n_{c}") for c in cols])
