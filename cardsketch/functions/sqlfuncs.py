"""Temporary SQL functions with SQL bodies, which the analyser inlines: no Python runs."""

from __future__ import annotations

from pyspark.sql import SparkSession

from .constants import gamma

BODIES = {
    "nb_bit(x BIGINT) RETURNS BIGINT": "(shiftrightunsigned(x, 4) | 1152921504606846976) & -(shiftrightunsigned(x, 4) | 1152921504606846976)",
    "nb_top(bitmap BIGINT) RETURNS INT": "CASE WHEN bitmap = 0 THEN 0 ELSE length(bin(bitmap)) END",
    "nb_nbr(bitmap BIGINT) RETURNS INT": "CASE WHEN bitmap < 2 THEN 1 ELSE CAST(shiftright(bitmap, length(bin(bitmap)) - 2) & 1 AS INT) END",
    "nb_term(top INT, nbr INT) RETURNS DOUBLE": "pow(2.0D, -top) * (3 - 2 * nbr)",
}


def register(spark: SparkSession) -> None:
    for head, body in BODIES.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")


def distinct_sql(table: str, column: str, m: int, seed: int = 42) -> str:
    """SQL that estimates the distinct values of a column; register() comes first."""
    return f"""
    WITH cells AS (
      SELECT pmod(xxhash64({2 * seed + 1}, {column}), {m}) AS bucket, bit_or(nb_bit(xxhash64({2 * seed}, {column}))) AS bitmap
      FROM {table} WHERE {column} IS NOT NULL GROUP BY 1)
    SELECT {gamma(m)!r}D * {m} * {m} / (coalesce(sum(nb_term(nb_top(bitmap), nb_nbr(bitmap))), 0) + {m} - count(*)) AS estimate FROM cells"""
