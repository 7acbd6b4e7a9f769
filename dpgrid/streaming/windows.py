"""Windowed counts over streams, and releases of closed windows.

Windows that do not overlap hold disjoint records, so a budget serves each of them alike; sliding windows share records and multiply
the cost by their overlap. Noise is keyed by the window's start: a batch that is replayed releases the same cells again.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from dpgrid.operators.grid import GridSpec, cell_of, inside
from dpgrid.plans.scratch import new_path


def event_stream(spark: SparkSession, folder: str, name: str = "events.parquet") -> DataFrame:
    """File stream of one table of a folder; the zone-less time becomes a timestamp, which watermarks need."""
    schema = spark.read.parquet(f"{folder}/{name}").schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", name).parquet(folder)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def clock_points(events: DataFrame) -> DataFrame:
    """Minute of the day and log value as coordinates."""
    return events.select("event_id", "user_id", "ts", ((F.hour("ts") * 60 + F.minute("ts")) / 1440.0).alias("x0"), (F.log(F.col("value") + 1.0) / F.log(F.lit(501.0))).alias("x1"))


def windowed_counts(points: DataFrame, cols: Sequence[str], spec: GridSpec, window: str = "1 hour", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """``start, cell, cnt`` per window; on a stream, a window appears once the watermark has passed its end."""
    framed = F.window("ts", window, slide) if slide else F.window("ts", window)
    sound = inside(points.withWatermark("ts", late), list(cols), spec)
    return sound.groupBy(framed.alias("win"), cell_of(list(cols), spec).alias("cell")).agg(F.count(F.lit(1)).alias("cnt")).select(F.col("win.start").alias("start"), "cell", "cnt")


def running_counts(points: DataFrame, cols: Sequence[str], spec: GridSpec) -> DataFrame:
    """``cell, cnt`` over all that has arrived, for update or complete output; state is one number per occupied cell."""
    return inside(points, list(cols), spec).groupBy(cell_of(list(cols), spec).alias("cell")).agg(F.count(F.lit(1)).alias("cnt"))


def events_in_windows(events: DataFrame, spans: DataFrame, bucket_seconds: int = 3600) -> DataFrame:
    """Join of events with the spans ``span, begin, finish`` that hold their time (begin <= ts < finish).

    Spans are listed under each bucket of time that they touch, so the join is by equality of bucket, with the exact
    comparison on what meets there.
    """
    bucket = lambda c: F.floor(F.unix_timestamp(c) / bucket_seconds)
    touched = F.explode(F.sequence(bucket(F.col("begin")), bucket(F.col("finish"))))
    listed = spans.select("span", "begin", "finish", touched.alias("bucket"))
    placed = events.withColumn("bucket", bucket(F.col("ts")))
    return placed.join(listed, "bucket").where((F.col("begin") <= F.col("ts")) & (F.col("ts") < F.col("finish"))).drop("bucket")


def session_counts(points: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """``user_id, start, n`` of each user's sessions."""
    made = points.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("win"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return made.select("user_id", F.col("win.start").alias("start"), "n")


def overlap_factor(window_seconds: int, slide_seconds: int) -> int:
    """Windows that a record falls in: what a sliding release multiplies the budget by."""
    return -(-window_seconds // slide_seconds)


def run_available(stream: DataFrame, label: str, each: Callable[[DataFrame, int], None] | None = None, mode: str = "append") -> DataFrame:
    """Run a stream over all input that is there, into a Parquet table of the shared folder (or through ``each``), and read the table."""
    spark = stream.sparkSession
    out, log = new_path(spark, label), new_path(spark, f"{label}_log")
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", log).trigger(availableNow=True)
    if each is None:
        query = writer.format("parquet").option("path", out).start()
    else:
        query = writer.foreachBatch(each).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out) if each is None else spark.createDataFrame([], stream.schema)


def releaser(spec: GridSpec, p: float, eps: float, key: str, method: str, path: str) -> Callable[[DataFrame, int], None]:
    """A ``foreachBatch`` function that releases every closed window of a batch of counts by the given method.

    Each window is a run of its own, numbered by its start, and files are named by batch: a replay overwrites itself.
    """
    from dpgrid.operators import methods
    from dpgrid.operators.privacy import runs_frame

    fn = {"noisy_counts": methods.release_noisy_counts, "trimmed": methods.release_trimmed, "sampled_cut": methods.release_sampled_cut}[method]

    def each(batch: DataFrame, number: int) -> None:
        batch = batch.persist()
        try:
            starts = [r[0] for r in batch.select(F.col("start").cast("long").alias("s")).distinct().orderBy("s").collect()]  # windows that closed just now
            made = None
            for s in starts:
                counts = batch.where(F.col("start").cast("long") == s).select("cell", "cnt")
                cells = fn(counts, spec, p, runs_frame(batch.sparkSession, [eps]), f"{key}|{s}").cells.select(F.lit(s).alias("start"), "wcell", "cluster")
                made = cells if made is None else made.unionByName(cells)
            if made is not None:
                made.write.mode("overwrite").parquet(f"{path}/batch={number}")
        finally:
            batch.unpersist()

    return each


def cap_stream(points: DataFrame, cap: int, idle: int | None = None) -> DataFrame:
    """The first ``cap`` rows of each user as they arrive, by custom state: one number per user.

    The cap is a promise for a user's whole life, so state stays for ever unless ``idle`` allows a fresh start: a user unseen for so many
    milliseconds of event time (which needs a watermark on ``ts``) is forgotten.
    """
    schema = points.schema

    def keep(_, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        (seen,) = state.get if state.exists else (0,)
        for pdf in batches:
            left = max(0, cap - seen)
            seen += len(pdf)
            yield pdf.head(left)
        state.update((seen,))
        if idle:
            state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs(), 0) + idle)

    return points.groupBy("user_id").applyInPandasWithState(keep, schema, "seen long", "append", GroupStateTimeout.EventTimeTimeout if idle else GroupStateTimeout.NoTimeout)


def label_stream(points: DataFrame, cells: DataFrame, cols: Sequence[str], spec: GridSpec) -> DataFrame:
    """New points with the cluster of the last released grid: a stream-static join that keeps no state."""
    from dpgrid.operators.methods import assign_points

    return assign_points(points, cells, cols, spec)


def unique_events(points: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event once; state is dropped behind the watermark."""
    return points.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def start_text(c: str = "start") -> Column:
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss").alias(c)
