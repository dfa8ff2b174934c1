"""Event streams: windows, sessions, duplicates, and pages encoded batch by batch."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..plans.fixtures import scratch_path

TRIP = "user_id long, start_us long, end_us long, xs array<double>, ys array<double>"
OPEN = "us array<long>, ids array<long>, xs array<double>, ys array<double>"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    d = spark.readStream.schema(schema).option("maxFilesPerTrigger", 4).parquet(f"{sf_dir}/events.parq*")
    return d.withColumn("ts", F.col("ts").cast("timestamp"))


def drained(df: DataFrame, mode: str) -> DataFrame:
    """The result of a stream over all that is there now, written as files: of the last batch (complete) or of all (append)."""
    spark, path = df.sparkSession, scratch_path(df.sparkSession, "drained")
    df.sparkSession.createDataFrame([], df.schema).write.parquet(f"{path}/batch=none")

    def write(batch: DataFrame, number: int) -> None:
        # a batch that runs again after a failure replaces its own files
        batch.write.mode("overwrite").parquet(f"{path}/batch={'none' if mode == 'complete' else number}")

    q = df.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", scratch_path(spark, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{path}/batch=*")


def tumbling(events: DataFrame, size: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", "10 minutes").groupBy(F.window("ts", size), "event_type").agg(F.count("*").alias("cnt"))


def sliding(events: DataFrame, size: str = "2 hours", step: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", "10 minutes").groupBy(F.window("ts", size, step)).agg(F.count("*").alias("cnt"))


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.withWatermark("ts", "10 minutes").groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("cnt"))


def without_repeats(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", "10 minutes").dropDuplicatesWithinWatermark(["event_id"])


def pages_of_stream(points: DataFrame, path: str, **options) -> None:
    """Each batch of a stream of (id, geometry) appended to a page table, as pages of its own."""
    from ..sources.page_table import pages

    def write(batch: DataFrame, number: int) -> None:
        # a batch that runs again after a failure writes its own folder again
        pages(batch, **options).write.mode("overwrite").parquet(f"{path}/batch={number}")

    points.writeStream.foreachBatch(write).option("checkpointLocation", scratch_path(points.sparkSession, "stream")).trigger(availableNow=True).start().awaitTermination()


def _trips(gap_us: int):
    """Trips of one user. Points wait in the state until the watermark is past the end of their trip and the gap."""

    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        parts = [np.array(state.get[k]) for k in range(4)] if state.exists else None
        cols = [parts] if parts else []
        if not state.hasTimedOut:
            cols += [[f[c].to_numpy() for c in ("us", "event_id", "x", "y")] for f in frames]
        us, ids, x, y = (np.concatenate(c) for c in zip(*cols, strict=True))
        order = np.lexsort((ids, us))
        us, ids, x, y = us[order], ids[order], x[order], y[order]
        starts = np.flatnonzero(np.r_[True, np.diff(us) >= gap_us])
        ends = np.r_[starts[1:], len(us)]
        closes_ms = (us[ends - 1]) // 1000 + gap_us // 1000
        done = int(np.searchsorted(closes_ms, state.getCurrentWatermarkMs(), "left"))
        if done < len(starts):
            at = starts[done]
            state.update(([*us[at:].tolist()], [*ids[at:].tolist()], [*x[at:].tolist()], [*y[at:].tolist()]))
            state.setTimeoutTimestamp(int(closes_ms[done]))
        else:
            state.remove()
        spans = list(zip(starts[:done], ends[:done], strict=True))
        yield pd.DataFrame({"user_id": [key[0]] * done, "start_us": [us[s] for s, _ in spans], "end_us": [us[e - 1] for _, e in spans], "xs": [x[s:e] for s, e in spans], "ys": [y[s:e] for s, e in spans]})

    return run


def trips(points: DataFrame, gap_minutes: int = 30) -> DataFrame:
    """MultiPoint trips (user_id, start_us, end_us, geometry) of a stream (user_id, event_id, ts, x, y), cut at pauses of ``gap_minutes``.

    A trip comes out once, when no point that is still let in can lengthen it; the state holds
    points of unfinished trips alone.
    """
    from ..functions import build

    d = points.withWatermark("ts", "10 minutes").select("user_id", "event_id", "ts", F.unix_micros("ts").alias("us"), "x", "y")
    t = d.groupBy("user_id").applyInPandasWithState(_trips(gap_minutes * 60_000_000), TRIP, OPEN, "append", GroupStateTimeout.EventTimeTimeout)
    return t.select("user_id", "start_us", "end_us", build.multipoint(F.arrays_zip(F.col("xs").alias("x"), F.col("ys").alias("y"))).alias("geometry"))


def late_rows(events: DataFrame) -> tuple[int, int]:
    """(rows read, rows the watermark kept out) of a stream without repeats, run over all that is there now.

    Raises if the session has dropped the progress of some batches
    (``spark.sql.streaming.numRecentProgressUpdates``): the counts would be short.
    """
    d = without_repeats(events)
    q = d.writeStream.format("noop").option("checkpointLocation", scratch_path(d.sparkSession, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    progress = {p["batchId"]: p for p in q.recentProgress}
    if progress and min(progress) > 0:
        raise ValueError(f"progress of batches before {min(progress)} is gone")
    return sum(p["numInputRows"] for p in progress.values()), sum(o["numRowsDroppedByWatermark"] for p in progress.values() for o in p["stateOperators"])
