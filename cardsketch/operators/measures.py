"""Accuracy and memory measures over tables of estimates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.constants import martingale_variance, variance

#: memory-variance products as published, for 64-bit hashes
PUBLISHED = {"pcsa": 38.9, "loglog": 10.11, "hll": 6.48, "nb": 5.46, "entropy": 1.98}


def accuracy(est: DataFrame, truth: str, by: list[str] = ()) -> DataFrame:
    """(by..., runs, bias, rel_var, rel_mse, rse) of column estimate against column truth."""
    r = F.col("estimate") / F.col(truth)
    return est.groupBy(*by).agg(F.count("*").alias("runs"), (F.avg(r) - 1).alias("bias"), F.var_pop(r).alias("rel_var"), F.avg(F.pow(r - 1, F.lit(2.0))).alias("rel_mse"), F.stddev_pop(r).alias("rse"))


def coverage(est: DataFrame, truth: str, by: list[str] = ()) -> DataFrame:
    return est.groupBy(*by).agg(F.avg(((F.col("lo") <= F.col(truth)) & (F.col(truth) <= F.col("hi"))).cast("double")).alias("coverage"))


def update_cost(df: DataFrame, col: str, cfg: SketchConfig, kinds: tuple[str, ...] = ("nb", "hll", "loglog", "pcsa")) -> list[tuple[str, int, float, float]]:
    """(method, rows, seconds, rows a second) of counting a column, of the engine's own ways and of exact counts.
    Each is run, so this is for measuring."""
    import time

    from . import exact
    from .estimators import estimate

    ways = {k: estimate(df, col, cfg, k) for k in kinds}
    ways |= {"approx_count_distinct": exact.builtin_approx(df, col), "hll_sketch_agg": exact.builtin_hll(df, col), "exact": exact.exact_distinct(df, col)}
    rows, out = df.count(), []
    for name, x in ways.items():
        began = time.perf_counter()
        x.collect()  # a row
        took = time.perf_counter() - began
        out.append((name, rows, took, rows / took))
    return out


def mvp(kind: str, m: int | None = None) -> float:
    """Bits times relative variance, of m cells or in the limit of many."""
    if kind == "entropy":
        return 4.69922 / 2.37326  # ideal code length over Fisher information, a cell
    base = kind.split("_")[-1]
    v = martingale_variance(base) if kind.startswith("mart") else variance(base, m)
    per = {"pcsa": 64, "loglog": 6, "hll": 6, "nb": 7, "tc_hll": 4, "tc_nb": 5, "mart_hll": 6, "mart_nb": 7}[kind]
    return per * v


def memory_ratio(a: str, b: str) -> float:
    """Memory of a over that of b at equal accuracy."""
    return mvp(a) / mvp(b)
