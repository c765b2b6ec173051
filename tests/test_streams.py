"""Streams in several batches: restarts, late rows, and the same rows run again."""

from pyspark.sql import functions as F

from cardsketch.config import portable
from cardsketch.operators import martingale
from cardsketch.sources.tables import load
from cardsketch.streaming import windows

COLUMNS = ["event_id", "ts", "user_id", "event_type"]


def rows(df):
    return sorted(map(str, df.collect()))


def test_first_seen_goes_on_after_a_restart(spark, sf_dir, tmp_path):
    x, cfg = load(spark, sf_dir, "events", COLUMNS), portable(64)
    want = martingale.martingale(x, "user_id", ["event_id"], cfg, "nb", ["event_type"]).select("event_type", "changes", F.round("est", 6), F.round("var", 4))
    n, path = x.count(), str(tmp_path / "in")
    windows.as_files(x.where(f"event_id < {n // 2}"), "event_id", 2, f"{path}/a")
    for part in range(2):
        f = windows.FirstSeen(spark, str(tmp_path / "table"), cfg, ["event_type"])
        f.run(windows.file_stream(spark, path, x.schema), "user_id", "event_id", str(tmp_path / "checkpoint"))
        if not part:
            windows.as_files(x.where(f"event_id >= {n // 2}"), "event_id", 3, f"{path}/b")
    assert f.last >= 4
    assert rows(f.estimates().select("event_type", "changes", F.round("est", 6), F.round("var", 4))) == rows(want)


def test_late_rows_count_nowhere(spark, sf_dir, tmp_path):
    """A row behind the watermark is dropped by the sketch and by the exact count alike; one within the delay counts."""
    x, path = load(spark, sf_dir, "events", COLUMNS), str(tmp_path / "in")
    windows.as_files(x, "event_id", 3, path)
    last = x.agg(F.max("ts")).first()[0]
    late = x.limit(1).select(F.lit(10**7).alias("event_id"), F.lit("2024-01-01 00:00:00").cast("timestamp_ntz").alias("ts"), F.lit(10**9).cast("long").alias("user_id"), "event_type")
    within = late.withColumn("ts", F.lit(last)).withColumn("user_id", F.lit(10**9 + 1).cast("long"))
    late.union(within).select(*[F.col(c).cast(t) for c, t in x.dtypes]).coalesce(1).write.parquet(f"{path}/part=late")
    s = windows.with_event_time(windows.file_stream(spark, path, x.schema), "1 day")
    cells = windows.drain(windows.windowed(s, "user_id", portable(64), "1 day"), "append")
    closed = windows.window_estimates(cells, portable(64)).where(F.col("start") == "2024-01-01").first()["estimate"]
    want = x.where("ts < '2024-01-02'").select("user_id").distinct().count()
    assert abs(closed / want - 1) < 0.4
    again = windows.windowed(windows.with_event_time(x.unionByName(late.select(*[F.col(c).cast(t) for c, t in x.dtypes]))), "user_id", portable(64), "1 day")
    counted = windows.window_estimates(again, portable(64)).where(F.col("start") == "2024-01-01").first()["estimate"]
    assert closed <= counted


def test_a_batch_that_is_run_again_changes_nothing(spark, sf_dir, tmp_path):
    x = load(spark, sf_dir, "events", COLUMNS)
    path = windows.as_files(x, "event_id", 2, str(tmp_path / "in"))
    s = lambda: windows.with_event_time(windows.file_stream(spark, path, x.schema))
    out = str(tmp_path / "out")
    a = rows(windows.drain(windows.windowed(s(), "user_id", portable(64), "1 day"), "append", out, str(tmp_path / "c1")))
    b = rows(windows.drain(windows.windowed(s(), "user_id", portable(64), "1 day"), "append", out, str(tmp_path / "c2")))
    assert a and a == b
