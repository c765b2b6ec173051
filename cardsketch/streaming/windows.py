"""Sketches over streams: windowed ORs in the state store, sessions, joins, and sequential sketches."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor
from pyspark.sql.streaming.state import GroupStateTimeout

from ..config import SketchConfig
from ..functions.hashing import split
from ..operators.estimators import from_sums, sums
from ..operators.martingale import trace
from ..operators.registers import nb_update
from ..sources.tables import scratch


def event_stream(spark: SparkSession, sf_dir: str, name: str = "events", files: int = 1) -> DataFrame:
    """A table's files as a stream; ts becomes a timestamp, which watermarks need."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/{name}.parquet*")


def as_files(df: DataFrame, order: str, batches: int, path: str) -> str:
    """df as `batches` files in a folder, ranges of a column, whose times of writing follow them, so that a stream
    takes them in that order; for replays."""
    low, high = df.agg(F.min(order), F.max(order)).first()
    for i in range(batches):
        a, b = low + (high - low + 1) * i // batches, low + (high - low + 1) * (i + 1) // batches
        df.where((F.col(order) >= a) & (F.col(order) < b)).coalesce(1).write.parquet(f"{path}/part={i:04d}")
    return path


def file_stream(spark: SparkSession, path: str, schema, files: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).option("recursiveFileLookup", "true").parquet(path)


def with_event_time(df: DataFrame, delay: str = "1 day") -> DataFrame:
    return df.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def windowed(df: DataFrame, col: str, cfg: SketchConfig, size: str, slide: str | None = None, by: list[str] = ()) -> DataFrame:
    """(start, by..., bucket, bitmap) per window; the state is one long for each filled cell."""
    x = df.withColumn("w", F.window("ts", size, slide) if slide else F.window("ts", size))
    x = split(x, col, cfg, ["w", *by])
    return x.groupBy("w", *by, "bucket").agg(F.bit_or("bit").alias("bitmap")).select(F.col("w.start").alias("start"), *by, "bucket", "bitmap")


def window_estimates(cells: DataFrame, cfg: SketchConfig, kind: str = "nb", by: list[str] = ()) -> DataFrame:
    keys = ["start", *by]
    return from_sums(sums(cells, cfg.m, keys), kind, cfg, keys).select(*keys, "estimate")


#: State store that transformWithState needs.
ROCKSDB = {"spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"}


def drain(stream: DataFrame, mode: str = "complete", out: str | None = None, checkpoint: str | None = None, conf: dict[str, str] | None = None) -> DataFrame:
    """Runs a stream over what is there now and returns its rows, through a table in the shared folder.  With the
    folders of an earlier run it goes on from there.  A batch that is run again overwrites what it wrote before.
    conf holds for this stream only: a stream keeps the settings that it was started with."""
    spark = stream.sparkSession
    out, checkpoint = out or scratch(spark), checkpoint or scratch(spark)

    def keep(batch: DataFrame, i: int) -> None:
        batch.write.mode("overwrite").parquet(out if mode == "complete" else f"{out}/batch={i}")

    before = {k: spark.conf.get(k, None) for k in conf or {}}
    for k, v in (conf or {}).items():
        spark.conf.set(k, v)
    try:
        q = stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(keep).start()
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def _first_arrivals(frames) -> tuple[pd.DataFrame, int]:
    """The first arrival of each bit of a batch, which alone can change a state, and the batch's rows."""
    seen, n = None, 0
    for f in frames:
        n += len(f)
        seen = (f if seen is None else pd.concat([seen, f])).sort_values("o").drop_duplicates(["bucket", "bit"])
    return seen, n


def _advance(state: tuple, seen: pd.DataFrame, n: int, m: int) -> tuple:
    """(top, nbr, total, est, var, rows) after first arrivals."""
    top, nbr, total, est, var, rows = state
    top, nbr = list(top), list(nbr)
    for cell, bit in zip(seen["bucket"].tolist(), seen["bit"].tolist()):
        a, b = top[cell], nbr[cell]
        c, d = nb_update(a, b, bit.bit_length())
        if (a, b) != (c, d):
            q = total / m
            est, var, total = est + 1 / q, var + (1 - q) / (q * q), total + 2.0**-c * (3 - 2 * d) - 2.0**-a * (3 - 2 * b)
            top[cell], nbr[cell] = c, d
    return top, nbr, total, est, var, rows + n


STATE = "top array<int>, nbr array<int>, total double, est double, var double, n long"


def stateful_martingale(stream: DataFrame, col: str, by: str, order: str, cfg: SketchConfig) -> DataFrame:
    """(by, rows_in, est, var) updates of a sequential sketch for each group: rows are taken by
    `order` inside a batch, batches in turn.  The state is the cells' pairs and three numbers."""
    x = split(stream, col, cfg, [by], [F.col(order).alias("o")])
    m = cfg.m

    def run(key, frames, state):
        old = state.get if state.exists else ([0] * m, [1] * m, float(m), 0.0, 0.0, 0)
        new = _advance(old, *_first_arrivals(frames), m)
        state.update(new)
        yield pd.DataFrame({by: [key[0]], "rows_in": [new[5]], "est": [new[3]], "var": [new[4]]})

    return x.groupBy(by).applyInPandasWithState(run, f"{by} {dict(x.dtypes)[by]}, rows_in long, est double, var double", STATE, "update", GroupStateTimeout.NoTimeout)


def transformed_martingale(stream: DataFrame, col: str, by: str, order: str, cfg: SketchConfig) -> DataFrame:
    """The same as a stateful processor; drain() needs conf=ROCKSDB for it."""
    x = split(stream, col, cfg, [by], [F.col(order).alias("o")])
    m = cfg.m

    class Sketch(StatefulProcessor):
        def init(self, handle) -> None:
            self.state = handle.getValueState("sketch", STATE)

        def handleInputRows(self, key, rows, timerValues):
            old = self.state.get() if self.state.exists() else ([0] * m, [1] * m, float(m), 0.0, 0.0, 0)
            new = _advance(tuple(old), *_first_arrivals(rows), m)
            self.state.update(new)
            yield pd.DataFrame({by: [key[0]], "rows_in": [new[5]], "est": [new[3]], "var": [new[4]]})

        def close(self) -> None:
            pass

    return x.groupBy(by).transformWithStateInPandas(Sketch(), f"{by} {dict(x.dtypes)[by]}, rows_in long, est double, var double", "update", "none")


class FirstSeen:
    """Sequential sketches of a stream without Python on its rows: each batch is aggregated to first arrivals and
    merged with those before, in a table a batch, so that a batch that is run again changes nothing.

    Order keys must rise from batch to batch.  A table has 64 m rows a group at most."""

    def __init__(self, spark: SparkSession, path: str, cfg: SketchConfig, by: list[str]):
        self.spark, self.path, self.cfg, self.by = spark, path, cfg, list(by)

    def run(self, stream: DataFrame, col: str, order: str, checkpoint: str) -> None:
        def merge(batch: DataFrame, i: int) -> None:
            new = split(batch, col, self.cfg, self.by, [F.col(order).alias("ord")])
            old = self.table(i - 1) if i else None
            rows = new if old is None else new.unionByName(old.select(new.columns))
            rows.groupBy(*self.by, "bucket", "bit").agg(F.min("ord").alias("ord")).write.mode("overwrite").parquet(f"{self.path}/{i}")
            self.last = i

        self.last = -1
        q = stream.writeStream.option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(merge).start()
        q.awaitTermination()

    def table(self, batch: int) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/{batch}")

    def estimates(self, kind: str = "nb") -> DataFrame:
        """(by..., changes, est, var) after the last batch."""
        t = trace(self.table(self.last), self.cfg, kind, self.by)
        return t.groupBy(*self.by).agg(F.count("*").alias("changes"), F.sum("inc").alias("est"), F.sum("var_inc").alias("var"))


def sessions(df: DataFrame, by: str, gap: str) -> DataFrame:
    """(by, start, end, rows) of each session."""
    return df.groupBy(by, F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n_rows")).select(by, F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n_rows")


def session_sketches(df: DataFrame, col: str, by: str, gap: str, cfg: SketchConfig) -> DataFrame:
    """(by, start, bucket, bitmap) of each session: a session's bounds depend on all its rows, so that a cell can't be
    a key of it; each of the m cells, a few, is an aggregate of its own.  Works on streams."""
    x = split(df, col, cfg, [by], [F.col("ts")])
    x = x.groupBy(by, F.session_window("ts", gap).alias("s")).agg(*[F.bit_or(F.when(F.col("bucket") == i, F.col("bit"))).alias(f"b{i}") for i in range(cfg.m)])
    cells = F.array(*[F.struct(F.lit(i).alias("bucket"), F.col(f"b{i}").alias("bitmap")) for i in range(cfg.m)])
    return x.select(by, F.col("s.start").alias("start"), F.inline(F.filter(cells, lambda c: c["bitmap"].isNotNull())))


def exact_stream(df: DataFrame, col: str, delay: str = "1 day") -> DataFrame:
    """The rows of a stream whose element is new within the watermark."""
    return with_event_time(df, delay).dropDuplicatesWithinWatermark([col])


def enriched(stream: DataFrame, table: DataFrame, key: str) -> DataFrame:
    """A stream joined with a table."""
    return stream.join(table, key)


def followed(left: DataFrame, right: DataFrame, key: str, within: str, delay: str = "1 day") -> DataFrame:
    """Pairs of rows of two streams with one key, the right one's at most `within` after the left one's; both have
    columns key, ts and event_id.  Rows older than that need no state."""
    a = with_event_time(left, delay).select(F.col(key), F.col("ts").alias("ts_a"), F.col("event_id").alias("id_a"))
    b = with_event_time(right, delay).select(F.col(key).alias("key_b"), F.col("ts").alias("ts_b"), F.col("event_id").alias("id_b"))
    on = (F.col(key) == F.col("key_b")) & (F.col("ts_b") >= F.col("ts_a")) & (F.col("ts_b") <= F.col("ts_a") + F.expr(f"interval {within}"))
    return a.join(b, on).select(key, "id_a", "id_b")
