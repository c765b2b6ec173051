"""Streams of the given tables: the orders of each supplier's line items are one.

So there are as many streams as suppliers, and a larger table has more of them.  An order counts at its first arrival
only, by its key or by its first day of shipping.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import SketchConfig
from ..functions.constants import alpha, gamma
from ..functions.hashing import rho, split
from ..operators import entropy, estimators, martingale, measures, tailcut
from . import simulate
from .tables import load, stored

CELLS = 32


def of_suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(stream, e, day): a row an order of a stream."""
    x = load(spark, sf_dir, "lineitem", ["l_suppkey", "l_orderkey", "l_shipdate"]).where("l_suppkey is not null and l_orderkey is not null")
    return x.groupBy(F.col("l_suppkey").alias("stream"), F.col("l_orderkey").alias("e")).agg(F.min("l_shipdate").alias("day"))


def _sized(x: DataFrame) -> DataFrame:
    return x.groupBy("stream").agg(F.count("*").alias("n"))


def _sequential(x: DataFrame, m: int, kinds: tuple[str, ...] = ("nb", "hll")) -> DataFrame:
    """(stream, method, estimate, own): own is the variance that the estimate states of itself."""
    cfg, out = SketchConfig(m), None
    first = stored(martingale.first_seen(x, "e", ["e"], cfg, ["stream"]))
    for k in kinds:
        t = martingale.trace(first, cfg, k, ["stream"]).groupBy("stream").agg(F.sum("inc").alias("estimate"), F.sum("var_inc").alias("own"))
        t = t.select("stream", F.lit(f"mart_{k}").alias("method"), "estimate", "own")
        out = t if out is None else out.union(t)
    return out


def _entropy(cells: DataFrame, m: int, depth: int = 44) -> DataFrame:
    """(stream, estimate, bits) of the entropy-coded bitmap of each stream."""
    x = cells.groupBy("stream").agg(F.array(*[F.sum(F.expr(f"shiftright(bitmap, {k}) & 1")) for k in range(depth)]).alias("levels"))

    def run(batches):
        for pdf in batches:
            if len(pdf):
                e, b = entropy.solve_all(np.stack(pdf["levels"]), m)
                yield pd.DataFrame({"stream": pdf["stream"], "estimate": e, "bits": b})

    return x.mapInPandas(run, "stream long, estimate double, bits double")


def measured_products(spark: SparkSession, sf_dir: str, m: int = CELLS) -> DataFrame:
    """(method, runs, bits_a_cell, m_var, measured, published): memory-variance products over all streams."""
    x = stored(of_suppliers(spark, sf_dir))
    bits = {"pcsa": 64.0, "loglog": 6.0, "hll": 6.0, "nb": 7.0, "mart_hll": 6.0, "mart_nb": 7.0}
    published = measures.PUBLISHED | {"mart_hll": 6 * 0.69, "mart_nb": 7 * 0.52}
    cells = stored(split(x, "e", SketchConfig(m), ["stream"]).groupBy("stream", "bucket").agg(F.bit_or("bit").alias("bitmap")))
    sums = stored(estimators.sums(cells, m, ["stream"]))
    e = _sequential(x, m).select("stream", "method", "estimate")
    for k in estimators.METHODS:
        e = e.union(estimators.from_sums(sums, k, SketchConfig(m), ["stream"]).select("stream", "method", "estimate"))
    pick = lambda d: F.create_map(*[F.lit(v) for kv in d.items() for v in kv])[F.col("method")]
    e = e.withColumn("bits", pick(bits)).unionByName(_entropy(cells, m).select("stream", F.lit("entropy").alias("method"), "estimate", (F.col("bits") / m).alias("bits")))
    e = e.join(_sized(x), "stream").groupBy("method").agg(F.count("*").alias("runs"), F.avg("bits").alias("bits_a_cell"), (F.var_samp(F.col("estimate") / F.col("n")) * m).alias("m_var"))
    return e.select("method", "runs", "bits_a_cell", "m_var", (F.col("bits_a_cell") * F.col("m_var")).alias("measured"), pick(published).alias("published"))


def own_variances(spark: SparkSession, sf_dir: str, m: int = CELLS) -> DataFrame:
    """(method, runs, true, own): the spread of sequential estimates, and the mean of the variances that they state of themselves."""
    x = stored(of_suppliers(spark, sf_dir))
    e, n = _sequential(x, m).join(_sized(x), "stream"), F.col("n")
    return e.groupBy("method").agg(F.count("*").alias("runs"), F.var_samp(F.col("estimate") / n).alias("true"), F.avg(F.col("own") / n / n).alias("own"))


def order_share(spark: SparkSession, sf_dir: str, m: int = CELLS, widths: tuple[int, ...] = (2, 3, 4)) -> DataFrame:
    """(width, runs, by_order, by_merge): the share of streams whose tail-cut sketch differs when the same orders come by
    day of shipping, not by key, or are counted as two halves that are merged."""
    x = of_suppliers(spark, sf_dir)
    x = split(x, "e", SketchConfig(m), ["stream"], [F.col("e").alias("e"), F.col("day").alias("day")]).select("stream", "e", "day", "bucket", rho(F.col("bit")).alias("k"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("e", ignore_index=True)
        other = pdf.sort_values(["day", "e"]).index.to_numpy()
        cell, k = pdf["bucket"].to_numpy(np.int64), pdf["k"].to_numpy(np.int64)
        return pd.DataFrame([(w, *simulate.differences(cell, k, other, m, w)) for w in widths], columns=["width", "o", "g"]).astype({"width": "int32"})

    x = x.groupBy("stream").applyInPandas(run, "width int, o boolean, g boolean")
    return x.groupBy("width").agg(F.count("*").alias("runs"), F.avg(F.col("o").cast("double")).alias("by_order"), F.avg(F.col("g").cast("double")).alias("by_merge"))


def _by_width(kind: str, m: int, widths: tuple[int, ...]):
    """From a stream's (bucket, k, ord): the estimates at its end, by width of the offsets."""
    c = (gamma(m) if kind == "nb" else alpha(m)) * m * m

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf, rows = pdf.sort_values("ord", ignore_index=True), []
        bucket, k = pdf["bucket"].to_numpy(), pdf["k"].to_numpy()
        first = ~pdf.duplicated(["bucket", "k"]).to_numpy()
        for w in widths:
            t, live = tailcut.TailCut(m, w, kind), first | (k >= 1 << w)
            for a, b in zip(bucket[live].tolist(), k[live].tolist()):
                t.add(a, b)
            rows.append((pdf["stream"][0], w, c / (2.0**-t.tops() * ((3 - 2 * t.nbr) if kind == "nb" else 1)).sum()))
        return pd.DataFrame(rows, columns=["stream", "width", "estimate"]).astype({"width": "int32"})
    return run


def width_errors(spark: SparkSession, sf_dir: str, m: int = CELLS, widths: tuple[int, ...] = (2, 3, 4, 5)) -> DataFrame:
    """(method, m, checkpoint, runs, bias, rel_mse, rel_mse_se, m_mse, width): tail-cut sketches at equal memory by width
    of the offsets, at the ends of all streams; checkpoint is their mean length."""
    x, out = stored(of_suppliers(spark, sf_dir)), None
    for name, ratio in simulate.PLOTS["c"]:
        kind, cells = name[3:], round(m * ratio)
        rows = tailcut.replay_rows(x, "e", ["e"], SketchConfig(cells), min(widths), ["stream"])
        e = rows.groupBy("stream").applyInPandas(_by_width(kind, cells, widths), "stream long, width int, estimate double").select("stream", "width", "estimate", F.lit(name).alias("method"), F.lit(cells).alias("m"))
        out = e if out is None else out.union(e)
    r = F.col("estimate") / F.col("n")
    y = out.join(_sized(x), "stream").groupBy("method", "m", "width")
    y = y.agg(F.avg("n").alias("checkpoint"), F.count("*").alias("runs"), (F.avg(r) - 1).alias("bias"), F.avg(F.pow(r - 1, F.lit(2.0))).alias("rel_mse"), (F.stddev_samp(F.pow(r - 1, F.lit(2.0))) / F.sqrt(F.count("*"))).alias("rel_mse_se"))
    return y.select("method", "m", "checkpoint", "runs", "bias", "rel_mse", "rel_mse_se", (F.col("m") * F.col("rel_mse")).alias("m_mse"), "width")
