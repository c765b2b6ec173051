"""Sizes of unions, intersections and differences from two sketches of equal configuration."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import SketchConfig
from ..sources.tables import stored
from .estimators import from_sums, sums, term
from .registers import gap_of, nbr_of, top_of


def set_sizes(a: DataFrame, b: DataFrame, cfg: SketchConfig, kind: str = "nb") -> DataFrame:
    """(n_a, n_b, n_union, n_both, n_only_a, jaccard); what is both is n_a + n_b - n_union, 0 at least."""
    x = a.withColumnRenamed("bitmap", "x").join(b.withColumnRenamed("bitmap", "y"), "bucket", "full")
    zero = F.lit(0).cast("long")
    sides = F.array(F.struct(F.lit("a").alias("side"), F.coalesce("x", zero).alias("bitmap")), F.struct(F.lit("b").alias("side"), F.coalesce("y", zero).alias("bitmap")), F.struct(F.lit("u").alias("side"), F.coalesce("x", zero).bitwiseOR(F.coalesce("y", zero)).alias("bitmap")))
    x = x.select("bucket", F.inline(sides)).where("bitmap <> 0")
    est = from_sums(sums(x, cfg.m, ["side"]), kind, cfg, ["side"])
    of = lambda s: F.coalesce(F.max(F.when(F.col("side") == s, F.col("estimate"))), F.lit(0.0))
    r = est.agg(of("a").alias("n_a"), of("b").alias("n_b"), of("u").alias("n_union"))
    both = F.greatest(F.lit(0.0), F.col("n_a") + F.col("n_b") - F.col("n_union"))
    return r.withColumn("n_both", both).withColumn("n_only_a", F.greatest(F.lit(0.0), F.col("n_union") - F.col("n_b"))).withColumn("jaccard", F.when(F.col("n_union") > 0, F.col("n_both") / F.col("n_union")).otherwise(0.0))


def pairwise_jaccard(sketch: DataFrame, group: str, cfg: SketchConfig, kind: str = "nb") -> DataFrame:
    """(a, b, jaccard) for the pairs of groups that have a cell in common, through those cells: sums of a union are those of
    both groups, put right in the cells that both have.  Rows are pairs by common cell, before a partial sum."""
    b = F.col("bitmap")
    # by cell what it adds to each sum; an empty cell adds 1 to either indicator
    terms = [(term("hll", top_of(b)) - 1).alias("s_hll"), (term("nb", top_of(b), nbr_of(b)) - 1).alias("s_nb"), top_of(b).cast("double").alias("s_top"), gap_of(b).cast("double").alias("s_gap")]
    names = ["s_hll", "s_nb", "s_top", "s_gap"]
    cells = stored(sketch.select(F.col(group).alias("g"), "bucket", "bitmap"))
    own = cells.select("g", *terms).groupBy("g").agg(F.count("*").alias("filled"), *[F.sum(n).alias(n) for n in names])
    both = cells.select(F.col("g").alias("a"), "bucket", F.col("bitmap").alias("x")).join(cells.select(F.col("g").alias("b"), "bucket", F.col("bitmap").alias("y")), "bucket").where("a < b")
    either = F.array(*[F.struct(F.lit(k).alias("sign"), v.alias("bitmap")) for k, v in ((1, F.col("x").bitwiseOR(F.col("y"))), (-1, F.col("x")), (-1, F.col("y")))])
    both = both.select("a", "b", F.inline(either)).select("a", "b", "sign", *terms).groupBy("a", "b").agg((F.sum("sign")).alias("filled"), *[F.sum(F.col("sign") * F.col(n)).alias(n) for n in names])
    side = lambda c: own.select(F.col("g").alias(c), *[F.col(n).alias(f"{c}_{n}") for n in ("filled", *names)])
    u = both.join(side("a"), "a").join(side("b"), "b")
    sized = lambda prefix: [(sum((F.col(f"{p}{n}") for p in prefix), F.lit(float(cfg.m) if n in ("s_hll", "s_nb") else 0))).cast("long" if n == "filled" else "double").alias(n) for n in ("filled", *names)]
    parts = []
    for name, prefix in (("n_union", ("", "a_", "b_")), ("n_a", ("a_",)), ("n_b", ("b_",))):
        parts.append(u.select("a", "b", F.lit(name).alias("side"), *sized(prefix)))
    est = from_sums(parts[0].union(parts[1]).union(parts[2]), kind, cfg, ["a", "b", "side"])
    of = lambda n: F.max(F.when(F.col("side") == n, F.col("estimate"))).alias(n)
    r = est.groupBy("a", "b").agg(of("n_union"), of("n_a"), of("n_b"))
    return r.select("a", "b", (F.greatest(F.lit(0.0), F.col("n_a") + F.col("n_b") - F.col("n_union")) / F.col("n_union")).alias("jaccard"))
