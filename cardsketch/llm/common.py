"""Helpers that several operators share: durable intermediate tables, global ranks, Arrow mapping."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.tables import discard, scratch, stored  # noqa: F401

#: Most rows of a table of keys that are sent to all tasks.
SENT = 1 << 20


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def ranked(df: DataFrame, keys: list[str], order: list[Column], name: str, spread: int, cells: Column | None = None) -> DataFrame:
    """Adds a gapless rank from 0 within each value of keys, without sorting a whole group in one task.

    Rows of a key are dealt over `spread` cells by a hash of the order columns; a cell's first rank
    is the number of rows in the key's earlier cells.  Only the cells' counts, `spread` a key at
    most, meet in one task.  Rows equal in all order columns are interchangeable.  With `cells`, cells
    that rise with the order columns, ranks do too.
    """
    cell = f"__{name}_cell"
    x = df.withColumn(cell, F.pmod(F.xxhash64(F.lit(7), *order), F.lit(spread)).cast("int") if cells is None else cells)
    by = Window.partitionBy(*keys).orderBy(cell)
    first = x.groupBy(*keys, cell).agg(F.count("*").alias("__n")).select(
        *[F.col(k).alias(f"__k{i}") for i, k in enumerate(keys)], F.col(cell).alias("__c"),
        (F.sum("__n").over(by) - F.col("__n")).alias("__first"))
    inside = Window.partitionBy(*keys, cell).orderBy(*order)
    on = F.col(cell) == F.col("__c")
    for i, k in enumerate(keys):
        on = on & F.col(k).eqNullSafe(F.col(f"__k{i}"))
    x = x.withColumn("__at", F.row_number().over(inside)).join(first, on)
    return x.withColumn(name, F.col("__first") + F.col("__at") - 1).drop(
        cell, "__c", "__first", "__at", *[f"__k{i}" for i in range(len(keys))])


def spread_for(rows: int, per_cell: int = 20_000, least: int = 64) -> int:
    """Cells for ranked(): they grow with the rows, so that a cell stays small."""
    return max(least, -(-rows // per_cell))


def sent(small: DataFrame, most: int | None = None) -> DataFrame:
    """small, marked for broadcast if it has `most` rows at most (SENT by default); beyond that a join
    moves both sides."""
    return F.broadcast(small) if small.limit((SENT if most is None else most) + 1).count() <= (SENT if most is None else most) else small


def text_hash(text_col: str) -> Column:
    return F.xxhash64(F.coalesce(F.col(text_col).cast("string"), F.lit("")))


def aliased(docs: DataFrame, *more: Column) -> DataFrame:
    """docs with its columns renamed c0, c1, ..., so that no other name can clash, and more columns."""
    return docs.select(*[F.col(f"`{c}`").alias(f"c{j}") for j, c in enumerate(docs.columns)], *more)


def named(x: DataFrame, docs: DataFrame) -> DataFrame:
    """The columns of aliased(docs) under their own names again."""
    return x.select(*[F.col(f"c{j}").alias(c) for j, c in enumerate(docs.columns)])


def keep_least(docs: DataFrame, member: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """The rows of docs, all columns, of which one stays of each group.

    member: (id, th, root, component_id), a row for each row of docs; th is text_hash, root names the group and
    component_id is its least id.  The row of that id stays, of several under it that of the least th, of
    rows equal in both any one.  Texts under one id that are in different groups all stay."""
    keys = member.groupBy("id", "th").agg(F.first("root").alias("root"), F.first("component_id").alias("c"), F.count("*").alias("n"))
    keys = stored(keys)
    lead = keys.where(F.col("id").eqNullSafe(F.col("c"))).groupBy("root").agg(F.min("th").alias("least"))
    lead = stored(lead)  # a join of two written tables can be split where a group is hot
    marked = keys.join(lead, "root").withColumn("stays", F.col("id").eqNullSafe(F.col("c")) & (F.col("th") == F.col("least")))
    marked = stored(marked.select(F.col("id").alias("k_id"), F.col("th").alias("k_th"), "stays", "n"))
    i, h = F.col(id_col).cast("long").alias("k_i"), text_hash(text_col).alias("k_h")
    on = F.col("k_i").eqNullSafe(F.col("k_id")) & (F.col("k_h") == F.col("k_th"))
    x = aliased(docs, i, h).join(sent(marked.where("not stays").select("k_id", "k_th")), on, "left_anti")
    again = marked.where("stays and n > 1").select("k_id", "k_th")
    if again.head(1):
        again = sent(again)
        x = x.join(again, on, "left_anti").unionByName(x.join(again, on, "left_semi").dropDuplicates(["k_i", "k_h"]))
    return named(x, docs)
