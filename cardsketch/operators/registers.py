"""Sketch rows: one OR of isolated bits per (group, cell) carries every mergeable sketch.

build() is one scan with partial aggregation: a task sends at most m rows a group.  A cell that no
element hit has no row.  top is the highest bit seen, nbr whether the bit under it was seen (1 where
there is none), gap the number of low bits seen without a break.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import SketchConfig
from ..functions.hashing import rho, split


def build(df: DataFrame, cols: str | list[str], cfg: SketchConfig, by: list[str] = (), where: Column | None = None) -> DataFrame:
    """(by..., bucket, bitmap)."""
    df = df if where is None else df.where(where)
    return split(df, cols, cfg, list(by)).groupBy(*by, "bucket").agg(F.bit_or("bit").alias("bitmap"))


def build_segments(df: DataFrame, cols: str | list[str], cfg: SketchConfig, segments: dict[str, Column]) -> DataFrame:
    """(segment, bucket, bitmap) of several conditions, which may overlap, from one scan and one aggregation."""
    x = split(df, cols, cfg, keep=[F.coalesce(c, F.lit(False)).alias(f"__s{i}") for i, c in enumerate(segments.values())])
    x = x.groupBy("bucket").agg(*[F.bit_or(F.when(F.col(f"__s{i}"), F.col("bit"))).alias(n) for i, n in enumerate(segments)])
    return x.unpivot(["bucket"], list(segments), "segment", "bitmap").where("bitmap is not null")


def top_of(bitmap: Column) -> Column:
    return rho(bitmap)


def nbr_of(bitmap: Column) -> Column:
    return F.when(bitmap < 2, 1).otherwise(F.call_function("shiftright", bitmap, F.length(F.bin(bitmap)) - 2).bitwiseAND(F.lit(1)).cast("int"))


def gap_of(bitmap: Column) -> Column:
    return F.bit_count(bitmap.bitwiseAND(F.bitwise_not(bitmap + 1)))


def pairs(sketch: DataFrame, by: list[str] = ()) -> DataFrame:
    """(by..., bucket, top, nbr): what the new sketch keeps; seven bits a cell."""
    b = F.col("bitmap")
    return sketch.select(*by, "bucket", top_of(b).cast("tinyint").alias("top"), nbr_of(b).cast("tinyint").alias("nbr"))


def as_mask(top: Column, nbr: Column) -> Column:
    """The two bits that a pair stands for; OR of masks is the merge of pairs."""
    one = F.lit(1).cast("long")
    high = F.when(top > 0, F.call_function("shiftleft", one, (top - 1).cast("int"))).otherwise(F.lit(0).cast("long"))
    low = F.when((top > 1) & (nbr == 1), F.call_function("shiftleft", one, (top - 2).cast("int"))).otherwise(F.lit(0).cast("long"))
    return high.bitwiseOR(low)


def merge(sketches: list[DataFrame], by: list[str] = ()) -> DataFrame:
    """The sketch of the union of streams, from sketch rows of equal configuration, lossless."""
    _mergeable(sketches)
    rows = sketches[0]
    for s in sketches[1:]:
        rows = rows.unionByName(s)
    return rows.groupBy(*by, "bucket").agg(F.bit_or("bitmap").alias("bitmap"))


def merge_pairs(sketches: list[DataFrame], by: list[str] = ()) -> DataFrame:
    """The same from (top, nbr) rows."""
    _mergeable(sketches)
    rows = [s.select(*by, "bucket", as_mask(F.col("top"), F.col("nbr")).alias("bitmap")) for s in sketches]
    return pairs(merge(rows, by), by)


def _mergeable(sketches: list[DataFrame]) -> None:
    for s in sketches:
        if any(f.metadata.get("sequential") or f.name in ("est", "q_before") for f in s.schema.fields):
            raise ValueError("sequential states depend on the order of arrival and cannot be merged")


def fold(sketch: DataFrame, m_new: int, by: list[str] = ()) -> DataFrame:
    """The sketch with m_new cells, a divisor of the old number."""
    return sketch.select(*by, (F.col("bucket") % m_new).cast("int").alias("bucket"), "bitmap").groupBy(*by, "bucket").agg(F.bit_or("bitmap").alias("bitmap"))


def nb_update(top: int, nbr: int, k: int) -> tuple[int, int]:
    """One cell after a draw of k: plain Python, for stateful streams and tests."""
    if k > top:
        return k, 1 if k == 1 or k - top == 1 and top > 0 else 0
    return top, 1 if k == top - 1 else nbr
