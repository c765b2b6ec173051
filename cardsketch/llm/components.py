"""Connected components of an edge table by alternating large-star and small-star steps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, stored


def _large_star(e: DataFrame) -> DataFrame:
    both = e.union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
    low = stored(both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m")))
    return both.where("b > a").join(low, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()


def _small_star(e: DataFrame) -> DataFrame:
    down = e.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    low = stored(down.groupBy("a").agg(F.min("b").alias("m")))
    linked = down.join(low, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return linked.union(low.select("a", F.col("m").alias("b"))).distinct()


def components(edges: DataFrame) -> DataFrame:
    """(a, b): links between longs.  Returns (node, root): root is the least node of its component.

    Each round's edges and minima are written to the shared folder, so lineage stays short and the joins
    of both have plain exchanges, which can be split at a hub; rounds grow with
    the logarithm of a component's width.  Nodes without an edge to another node are not returned.
    """
    e = stored(edges.where("a <> b").distinct())
    seen = None
    while True:
        n = stored(_small_star(_large_star(e)))
        mark = tuple(n.agg(F.count("*"), F.expr("bit_xor(xxhash64(a, b))"), F.sum(F.expr("pmod(xxhash64(b, a), 1000003)"))).first())
        discard(e)
        e = n
        if mark == seen:
            break
        seen = mark
    roots = e.select(F.col("b").alias("node")).distinct().select("node", F.col("node").alias("root"))
    return e.select(F.col("a").alias("node"), F.col("b").alias("root")).union(roots)
