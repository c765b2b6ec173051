"""Answers over stored daily sketches: any range of days is a merge, raw rows are not read."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import SketchConfig
from ..operators.estimators import from_sums, sums
from ..operators.registers import build
from ..sources.tables import save_sketch


class SketchStore:
    """Sketch rows by (day, keys...) at a path; days are folders, so a range prunes folders."""

    def __init__(self, spark, path: str, cfg: SketchConfig, keys: list[str] = ()):
        self.spark, self.path, self.cfg, self.keys = spark, path, cfg, list(keys)

    def write(self, df: DataFrame, cols: str | list[str], day, mode: str = "overwrite") -> None:
        save_sketch(build(df.withColumn("day", F.to_date(day)), cols, self.cfg, ["day", *self.keys]), self.path, "day", mode)

    def answer(self, first: str, last: str, by: list[str] = (), kind: str = "nb") -> DataFrame:
        rows = self.spark.read.parquet(self.path).where(F.col("day").between(F.lit(first).cast("date"), F.lit(last).cast("date")))
        merged = rows.groupBy(*by, "bucket").agg(F.bit_or("bitmap").alias("bitmap"))
        return from_sums(sums(merged, self.cfg.m, by), kind, self.cfg, by)


def distinct_cube(df: DataFrame, cols: str | list[str], keys: list[str], cfg: SketchConfig, sets: list[list[str]], kind: str = "nb") -> DataFrame:
    """(keys..., set_id, estimate) for grouping sets: raw rows are aggregated once, into sketch rows, which alone are
    expanded; the cell is in every set."""
    s = build(df, cols, cfg, keys)
    cube = s.groupingSets([[*[F.col(k) for k in g], F.col("bucket")] for g in sets], *keys, "bucket").agg(F.bit_or("bitmap").alias("bitmap"), F.grouping_id(*keys, "bucket").alias("gid"))
    # in the id a bit is 1 for each column that a set leaves out, the last column's lowest
    ids = [sum((k not in g) << (len(keys) - i) for i, k in enumerate(keys)) for g in sets]
    number = F.coalesce(*[F.when(F.col("gid") == v, F.lit(i)) for i, v in enumerate(ids)])
    x = cube.withColumn("set_id", number)
    return from_sums(sums(x, cfg.m, [*keys, "set_id"]), kind, cfg, [*keys, "set_id"]).select(*keys, "set_id", "estimate")


def profile(df: DataFrame, cols: list[str], cfg: SketchConfig, kind: str = "nb") -> DataFrame:
    """(name, estimate) of every column from one scan: columns become rows before they are hashed."""
    x = df.select(*[F.col(c).cast("string").alias(c) for c in cols]).unpivot([], cols, "name", "value")
    return from_sums(sums(build(x, "value", cfg, ["name"]), cfg.m, ["name"]), kind, cfg, ["name"]).select("name", "estimate")


def join_size(n_left: float, n_right: float, rows_left: int, rows_right: int) -> float:
    """Rows of an equi-join, keys being spread evenly and the lesser set contained in the other."""
    return rows_left * rows_right / max(n_left, n_right, 1.0)


def join_estimate(left: DataFrame, a: str, right: DataFrame, b: str, cfg: SketchConfig) -> DataFrame:
    """(rows): join_size from one scan of each side's key."""
    def side(x: DataFrame, c: str, n: str) -> DataFrame:
        e = from_sums(sums(build(x, c, cfg), cfg.m), "nb", cfg).select(F.col("estimate").alias(f"d_{n}"))
        return e.crossJoin(F.broadcast(x.agg(F.count("*").cast("double").alias(f"n_{n}"))))

    both = side(left, a, "l").crossJoin(F.broadcast(side(right, b, "r")))  # one row each
    return both.select((F.col("n_l") * F.col("n_r") / F.greatest("d_l", "d_r", F.lit(1.0))).alias("rows"))
