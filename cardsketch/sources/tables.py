"""Reading the tables and storing sketches."""

from __future__ import annotations

import re
import uuid

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
#: Used only by local sessions that name no shared folder, as in tests.
FALLBACK_DIR = "/tmp/checkpoints/cardsketch"


def load(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def load_as(spark: SparkSession, fmt: str, path: str, schema=None, **options) -> DataFrame:
    """csv, json, orc, text or parquet."""
    r = spark.read.format(fmt).options(**options)
    return (r.schema(schema) if schema else r).load(path)


def register(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> None:
    for n in names:
        load(spark, sf_dir, n).createOrReplaceTempView(n)


def scratch(spark: SparkSession) -> str:
    """A new path in the folder that driver and executors share: spark.checkpoint.dir, or the context's
    checkpoint folder.  A local session may do without one; on a cluster that is an error, as executors
    would write to disks that others cannot read."""
    sc = spark.sparkContext
    base = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not base:
        if not re.fullmatch(r"local(\[.*\])?", sc.master):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = FALLBACK_DIR
    return f"{base.rstrip('/')}/t{uuid.uuid4().hex}"


def stored(df: DataFrame) -> DataFrame:
    """df, written once as Parquet to the shared folder and read back: lineage ends there, and a
    lost executor costs no recomputation."""
    path = scratch(df.sparkSession)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.stored_at = path
    return out


def discard(df: DataFrame) -> None:
    """Deletes what stored() wrote for df, when nothing will read it again."""
    spark = df.sparkSession
    p = spark._jvm.org.apache.hadoop.fs.Path(df.stored_at)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def save_sketch(sketch: DataFrame, path: str, partition: str | None = None, mode: str = "overwrite") -> None:
    """Sketch rows as Parquet, one folder a day (or another column)."""
    w = sketch.write.mode(mode)
    (w.partitionBy(partition) if partition else w).parquet(path)
