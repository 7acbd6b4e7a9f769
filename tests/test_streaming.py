"""Windows over streams: late rows, replays, sliding cost, unique events."""

import datetime as dt
import os
import time

from pyspark.sql import functions as F

from dpgrid.operators.grid import unit
from dpgrid.streaming import windows as win

SCHEMA = "event_id long, user_id long, ts timestamp, x0 double, x1 double"


def write(spark, folder, name, rows):
    spark.createDataFrame([(i, u, dt.datetime(2024, 1, 1) + dt.timedelta(minutes=m), 0.5, 0.5) for i, u, m in rows], SCHEMA).coalesce(1).write.parquet(f"{folder}/{name}")
    part = next(f for f in os.listdir(f"{folder}/{name}") if f.endswith(".parquet"))
    os.rename(f"{folder}/{name}/{part}", f"{folder}/in/{name}.parquet")
    time.sleep(1.1)  # files are taken in order of their time


def run(spark, folder, plan, sink):
    stream = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in")
    q = plan(stream).writeStream.format("parquet").option("path", f"{folder}/{sink}").option("checkpointLocation", f"{folder}/{sink}_log").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{folder}/{sink}").collect()


def test_late_rows_are_dropped_and_events_counted_once(spark, tmp_path):
    folder = str(tmp_path)
    os.mkdir(f"{folder}/in")
    write(spark, folder, "a", [(1, 1, 10), (2, 1, 80), (3, 2, 300), (3, 2, 300)])
    write(spark, folder, "b", [(5, 2, 540)])
    write(spark, folder, "c", [(4, 1, 15), (6, 2, 560), (3, 2, 300)])
    got = run(spark, folder, lambda s: win.windowed_counts(s, ["x0", "x1"], unit(4)), "tumbling")
    by_start = {r["start"].hour: r["cnt"] for r in got}
    assert by_start == {0: 1, 1: 1, 5: 3}  # minute 15 came after the watermark had passed its window; the last window is still open
    unique = run(spark, folder, win.unique_events, "unique")
    assert sorted(r["event_id"] for r in unique if r["event_id"] == 3) == [3]


def test_replayed_release_is_the_same(spark, tmp_path):
    rows = [(dt.datetime(2024, 1, d), c, n) for d in (1, 2) for c, n in ((0, 40), (1, 30), (9, 55), (40, 70))]
    batch = spark.createDataFrame(rows, "start timestamp, cell long, cnt long")
    each = win.releaser(unit(8), 0.25, 2.0, "secret", "trimmed", str(tmp_path))
    each(batch, 0)
    first = sorted(map(tuple, spark.read.parquet(f"{tmp_path}/batch=0").collect()))
    each(batch.repartition(5), 0)
    assert sorted(map(tuple, spark.read.parquet(f"{tmp_path}/batch=0").collect())) == first and first
    assert spark.read.parquet(str(tmp_path)).select("start").distinct().count() == 2


def test_sliding_windows_multiply_the_budget():
    assert win.overlap_factor(7200, 3600) == 2 and win.overlap_factor(3600, 3600) == 1


def test_batch_and_stream_agree(spark, tmp_path):
    folder = str(tmp_path)
    os.mkdir(f"{folder}/in")
    write(spark, folder, "a", [(i, i % 3, i * 7) for i in range(60)] + [(99, 1, 9999)])
    streamed = {(r["start"], r["cell"]): r["cnt"] for r in run(spark, folder, lambda s: win.windowed_counts(s, ["x0", "x1"], unit(4)), "agree")}
    batch = win.windowed_counts(spark.read.parquet(f"{folder}/in"), ["x0", "x1"], unit(4)).where(F.col("start") < "2024-01-02").collect()
    assert streamed == {(r["start"], r["cell"]): r["cnt"] for r in batch}
