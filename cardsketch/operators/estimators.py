"""Estimates from sketch rows: a second, tiny aggregation over cells, then arithmetic.

Cells without a row count as empty, so the sums add m less the number of rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import SketchConfig
from ..functions.constants import LOGLOG, PHI, alpha, gamma, variance
from .registers import build, gap_of, nbr_of, top_of

METHODS = ("nb", "hll", "loglog", "pcsa")


def term(kind: str, top: Column, nbr: Column | None = None) -> Column:
    t = F.pow(F.lit(2.0), -top.cast("double"))
    return t * (3 - 2 * nbr) if kind == "nb" else t


def sums(sketch: DataFrame, m: int, by: list[str] = (), columns: tuple[Column, Column] | None = None) -> DataFrame:
    """(by..., filled, s_hll, s_nb, s_top, s_gap) of each group; one row without groups."""
    if columns:
        top, nbr, gap = *columns, F.lit(0)
    else:
        b = F.col("bitmap")
        top, nbr, gap = top_of(b), nbr_of(b), gap_of(b)
    x = sketch.select(*by, top.alias("t"), nbr.alias("n"), gap.alias("g"))
    empty = F.lit(float(m)) - F.count("*")
    zero = lambda c: F.coalesce(F.sum(c), F.lit(0.0))
    return x.groupBy(*by).agg(
        F.count("*").alias("filled"), (zero(term("hll", F.col("t"))) + empty).alias("s_hll"), (zero(term("nb", F.col("t"), F.col("n"))) + empty).alias("s_nb"),
        F.coalesce(F.sum(F.col("t").cast("double")), F.lit(0.0)).alias("s_top"), F.coalesce(F.sum(F.col("g").cast("double")), F.lit(0.0)).alias("s_gap"))


def raw(kind: str, m: int) -> Column:
    if kind == "nb":
        return F.lit(gamma(m) * m * m) / F.col("s_nb")
    if kind == "hll":
        return F.lit(alpha(m) * m * m) / F.col("s_hll")
    mean = (F.col("s_top") if kind == "loglog" else F.col("s_gap")) / m
    return F.lit(LOGLOG * m if kind == "loglog" else m / PHI) * F.pow(F.lit(2.0), mean)


def from_sums(s: DataFrame, kind: str, cfg: SketchConfig, by: list[str] = ()) -> DataFrame:
    """(by..., method, m, estimate, rse, lo, hi, regime, bits)."""
    m, r = cfg.m, raw(kind, cfg.m)
    empty = F.lit(m) - F.col("filled")
    linear = F.lit(float(m)) * F.log(F.lit(float(m)) / empty)
    small = (r < cfg.threshold * m) & (empty > 0) if cfg.small_range and kind in ("nb", "hll") else F.lit(False)
    est = F.when(F.col("filled") == 0, 0.0).when(small, linear).otherwise(r)
    rse = (variance(kind, m if kind in ("nb", "hll") else None) / m) ** 0.5
    x = s.withColumn("estimate", est).withColumn("regime", F.when(F.col("filled") == 0, "empty").when(small, "linear").otherwise("raw"))
    e = F.col("estimate")
    return x.select(*by, F.lit(kind).alias("method"), F.lit(m).alias("m"), "estimate", F.lit(rse).alias("rse"), (e * (1 - 1.96 * rse)).alias("lo"), (e * (1 + 1.96 * rse)).alias("hi"), "regime", F.lit(memory_bits(kind, m)).cast("long").alias("bits"))


def estimate(df: DataFrame, cols: str | list[str], cfg: SketchConfig, kind: str = "nb", by: list[str] = ()) -> DataFrame:
    """Distinct elements of cols in each group."""
    return from_sums(sums(build(df, cols, cfg, by), cfg.m, by), kind, cfg, by)


def all_estimates(df: DataFrame, cols: str | list[str], cfg: SketchConfig, by: list[str] = ()) -> DataFrame:
    """Every mergeable method from one scan and one set of sums."""
    s = sums(build(df, cols, cfg, by), cfg.m, by)
    x = s.select(*by, *[raw(k, cfg.m).alias(k) for k in METHODS])
    return x.unpivot(list(by), list(METHODS), "method", "estimate")


def bitmap_estimate(df: DataFrame, cols: str | list[str], cfg: SketchConfig, by: list[str] = ()) -> DataFrame:
    """One coupon bitmap a group: 2**gap / phi."""
    one = SketchConfig(m=1, family=cfg.family, seed=cfg.seed)
    x = build(df, cols, one, by)
    return x.select(*by, gap_of(F.col("bitmap")).alias("gap"), (F.pow(F.lit(2.0), gap_of(F.col("bitmap"))) / PHI).alias("estimate"))


def change_probability(sketch: DataFrame, m: int, by: list[str] = ()) -> DataFrame:
    """(by..., q_nb, q_hll): the chance that a new element changes the state."""
    return sums(sketch, m, by).select(*by, (F.col("s_nb") / m).alias("q_nb"), (F.col("s_hll") / m).alias("q_hll"))


def memory_bits(kind: str, m: int) -> int:
    """Packed bits of a sketch for 64-bit hashes."""
    per = {"bitmap": 64, "pcsa": 64, "loglog": 6, "hll": 6, "nb": 7, "tc_hll": 4, "tc_nb": 5, "mart_hll": 6, "mart_nb": 7}[kind]
    return per * m + (64 if kind.startswith("mart") else 6 if kind.startswith("tc") else 0)
