"""Sequential estimators, from a parallel plan.

Only the first arrival of each (cell, bit) can change a lossless sketch, so the stream shrinks to at
most 64 m rows a group by one aggregation with partial sums; windows over those give each change and
the probability, in the state before it, that a new element changes the state.  The estimate
adds 1 / P at each change; its own variance estimate adds (1 - P) / P**2.  The order must be total.
Such states cannot be merged.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..config import SketchConfig
from ..functions.hashing import split
from .estimators import term
from .registers import nbr_of, top_of

KINDS = ("nb", "hll", "loglog", "pcsa")


#: Marks columns of states that depend on the order of arrival.
SEQUENTIAL = {"sequential": True}


def packed_order(day: Column, key: Column, bits: int = 40) -> Column:
    """A date and a key under 2**bits as one long, which aggregates by hash where a struct has to be sorted."""
    return F.call_function("shiftleft", F.datediff(F.to_date(day), F.lit("1970-01-01").cast("date")).cast("long"), F.lit(bits)) + key.cast("long")


def order_of(order: list[str]) -> Column:
    return (F.col(order[0]) if len(order) == 1 else F.struct(*order)).alias("ord")


def first_seen(df: DataFrame, cols: str | list[str], order: list[str], cfg: SketchConfig, by: list[str] = ()) -> DataFrame:
    """(by..., bucket, bit, ord): the first arrival of each bit of each cell; ord is the order column, or a struct of several."""
    x = split(df, cols, cfg, list(by), [order_of(order)])
    return x.groupBy(*by, "bucket", "bit").agg(F.min("ord").alias("ord"))


def trace(first: DataFrame, cfg: SketchConfig, kind: str = "nb", by: list[str] = ()) -> DataFrame:
    """(by..., ord, bucket, bit, q_before, inc, var_inc): the changes of state, with their increments."""
    if kind not in KINDS:
        raise ValueError(kind)
    by = list(by)
    x = first.withColumn("__g", F.lit(0))  # a window without a key warns
    if kind == "pcsa":
        x = x.withColumn("delta", -(F.lit(0.5) / F.col("bit")))
    else:
        own = Window.partitionBy(*by, "bucket").orderBy("ord")
        before = F.coalesce(F.bit_or("bit").over(own.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0).cast("long"))
        x = x.withColumn("before", before)

        def of(b: Column) -> Column:
            return term("nb" if kind == "nb" else "hll", top_of(b), nbr_of(b))

        x = x.withColumn("delta", of(F.col("before").bitwiseOR(F.col("bit"))) - of(F.col("before"))).where("delta <> 0")
    run = Window.partitionBy("__g", *by).orderBy("ord").rowsBetween(Window.unboundedPreceding, -1)
    q = (F.lit(float(cfg.m)) + F.coalesce(F.sum("delta").over(run), F.lit(0.0))) / cfg.m
    x = x.withColumn("q_before", q)
    return x.select(*by, "ord", "bucket", "bit", F.col("q_before").alias("q_before", metadata=SEQUENTIAL), (1 / F.col("q_before")).alias("inc"), ((1 - F.col("q_before")) / F.pow("q_before", F.lit(2.0))).alias("var_inc"))


def martingale(df: DataFrame, cols: str | list[str], order: list[str], cfg: SketchConfig, kind: str = "nb", by: list[str] = ()) -> DataFrame:
    """(by..., changes, est, var)."""
    t = trace(first_seen(df, cols, order, cfg, by), cfg, kind, by)
    return t.groupBy(*by).agg(F.count("*").alias("changes"), F.coalesce(F.sum("inc"), F.lit(0.0)).alias("est", metadata=SEQUENTIAL), F.coalesce(F.sum("var_inc"), F.lit(0.0)).alias("var"))


def trace_at(t: DataFrame, checkpoints: DataFrame, by: list[str] = ()) -> DataFrame:
    """(by..., checkpoint, est): the estimate after all changes up to each checkpoint (column `at`,
    of the type of the first order column, and by...): an as-of lookup by union and a running sum."""
    by = list(by)
    kind = t.schema["ord"].dataType
    x = t.select(*by, F.col(f"ord.{kind.names[0]}" if isinstance(kind, StructType) else "ord").alias("at"), F.lit(0).alias("kind"), "inc")
    x = x.unionByName(checkpoints.select(*by, "at", F.lit(1).alias("kind"), F.lit(0.0).alias("inc"))).withColumn("__g", F.lit(0))
    run = Window.partitionBy("__g", *by).orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, 0)
    return x.withColumn("est", F.sum("inc").over(run)).where("kind = 1").select(*by, F.col("at").alias("checkpoint"), "est")
