"""Tail-cut sketches: a base and short offsets.  Lossy, and dependent on order and merge path."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import SketchConfig
from ..functions.hashing import rho, split
from .estimators import from_sums, sums
from .martingale import first_seen, order_of
from .registers import pairs


def clamp(p: DataFrame, m: int, width: int = 4, by: list[str] = ()) -> DataFrame:
    """(by..., bucket, top, nbr) decoded from offsets of `width` bits over the least register of the
    group (0 if a cell is empty): what a sketch written to rest at one moment keeps."""
    least, cut = F.when(F.count("*").over(Window.partitionBy("__g", *by)) < m, 0).otherwise(F.min("top").over(Window.partitionBy("__g", *by))), F.lit((1 << width) - 1)
    x = p.withColumn("__g", F.lit(0)).withColumn("base", least)  # m rows a group at most
    return x.select(*by, "bucket", F.least("top", F.col("base") + cut).cast("tinyint").alias("top"), "nbr")


def snapshot(sketch: DataFrame, cfg: SketchConfig, kind: str = "nb", width: int = 4, by: list[str] = ()) -> DataFrame:
    x = clamp(pairs(sketch, by), cfg.m, width, by)
    return from_sums(sums(x, cfg.m, by, (F.col("top"), F.col("nbr"))), kind, cfg, by).withColumn("method", F.lit(f"tc_{kind}"))


class TailCut:
    """One sketch under sequential updates."""

    def __init__(self, m: int, width: int = 4, kind: str = "nb"):
        self.off, self.nbr = np.zeros(m, np.int64), np.ones(m, np.int64)
        self.base, self.most, self.kind = 0, (1 << width) - 1, kind

    def add(self, cell: int, k: int) -> None:
        k = min(k, self.base + self.most)
        top = self.base + int(self.off[cell])
        if k > top:
            self.nbr[cell] = 1 if k == 1 or (k == top + 1 and top > 0) else 0
            self.off[cell] = k - self.base
            if self.off.min() > 0:
                low = int(self.off.min())
                self.base += low
                self.off -= low
        elif k == top - 1:
            self.nbr[cell] = 1

    def tops(self) -> np.ndarray:
        return self.off + self.base

    def merged(self, other: TailCut) -> TailCut:
        """The lossy merge: decode, keep the larger, cut anew."""
        out = TailCut(len(self.off), kind=self.kind)
        out.most = self.most
        a, b = self.tops(), other.tops()
        top = np.maximum(a, b)
        near = np.where(a == b, self.nbr | other.nbr, np.where(a > b, np.where(a - b == 1, 1, self.nbr), np.where(b - a == 1, 1, other.nbr)))
        out.base = int(top.min())
        out.off, out.nbr = np.minimum(top - out.base, self.most), np.where(top <= 1, 1, near)
        return out


def replay_rows(df: DataFrame, cols: str | list[str], order: list[str], cfg: SketchConfig, width: int, by: list[str]) -> DataFrame:
    """The rows that fix a sequential tail-cut state: first arrivals, and draws beyond the cut, whose
    repeats may count.  At width 4 the latter are one row in 2**15, at width 2 one in 8: a group's
    meet in one task, so small widths are for experiments."""
    ord_ = order_of(order)
    first = first_seen(df, cols, order, cfg, by)
    far = split(df, cols, cfg, by, [ord_]).where(F.col("bit") >= F.lit(1 << ((1 << width) - 1)).cast("long")).select(*by, "bucket", "bit", "ord")
    return first.union(far).distinct().select(*by, "bucket", rho(F.col("bit")).cast("int").alias("k"), "ord")


def sequential(df: DataFrame, cols: str | list[str], order: list[str], cfg: SketchConfig, kind: str = "nb", width: int = 4, by: list[str] = ()) -> DataFrame:
    """(by..., bucket, top, nbr) as a sequential tail-cut sketch ends, for each group."""
    by, m = list(by), cfg.m
    rows = replay_rows(df, cols, order, cfg, width, by).withColumn("__g", F.lit(0))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        t = TailCut(m, width, kind)
        whole = [v if np.isscalar(v) or not hasattr(v, "__len__") else tuple(v.values()) if isinstance(v, dict) else tuple(v) for v in pdf["ord"]]
        x = pdf.assign(o=whole).sort_values("o")
        for cell, k in zip(x["bucket"], x["k"]):
            t.add(int(cell), int(k))
        out = pd.DataFrame({"bucket": np.arange(m, dtype=np.int32), "top": t.tops().astype(np.int32), "nbr": t.nbr.astype(np.int32)})
        for c in by:
            out[c] = pdf[c].iloc[0]
        return out[[*by, "bucket", "top", "nbr"]].query("top > 0")

    kinds = ", ".join(f"{c} {dict(df.dtypes)[c]}" for c in by)
    return rows.groupBy("__g", *by).applyInPandas(run, f"{kinds + ', ' if kinds else ''}bucket int, top int, nbr int")


def estimate(cells: DataFrame, cfg: SketchConfig, kind: str = "nb", by: list[str] = ()) -> DataFrame:
    return from_sums(sums(cells, cfg.m, by, (F.col("top"), F.col("nbr"))), kind, cfg, by).withColumn("method", F.lit(f"tc_{kind}"))


def merge_cells(a: DataFrame, b: DataFrame, m: int, width: int = 4) -> DataFrame:
    """The lossy merge of decoded (bucket, top, nbr) rows."""
    from .registers import merge_pairs

    return clamp(merge_pairs([a, b]), m, width)
