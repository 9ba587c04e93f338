"""Running and windowed sketches of an update stream; state is rows * cols cells per window.

Updates stream in as (event time, coord, delta).  The sketch is an aggregation on (row, bucket), so
its state is independent of the number of coordinates and of events.  ``fold_batches`` keeps a
store that a replayed micro-batch does not change; ``keep_residuals`` is a stateful operator with
time-out for per-key remainders.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from gradsift.operators.hashing import HashFamily


def spread(updates: DataFrame, fam: HashFamily, *keep: str) -> DataFrame:
    """Cell rows (row, bucket, signed delta) of updates; works on batch and streaming frames."""
    return updates.select(*keep, F.col("delta").alias("_d"), F.inline(fam.cells_of(F.col("coord")))).select(*keep, "row", "bucket", (F.col("_d") * F.col("sign")).alias("cell"))


def stream_sketch(updates: DataFrame, fam: HashFamily, time: str | None = None, window: str | None = None, slide: str | None = None, watermark: str | None = None) -> DataFrame:
    """Running cells, or cells per tumbling or sliding window of event time."""
    if watermark:
        updates = updates.withWatermark(time, watermark)
    if not window:
        return spread(updates, fam).groupBy("row", "bucket").agg(F.sum("cell").alias("cell"))
    rows = spread(updates, fam, time)
    return rows.groupBy(F.window(time, window, slide) if slide else F.window(time, window), "row", "bucket").agg(F.sum("cell").alias("cell"))


def session_sketch(updates: DataFrame, fam: HashFamily, time: str, gap: str, watermark: str) -> DataFrame:
    """Cells per session: updates less than ``gap`` apart belong together."""
    rows = spread(updates.withWatermark(time, watermark), fam, time)
    return rows.groupBy(F.session_window(time, gap), "row", "bucket").agg(F.sum("cell").alias("cell"))


def once(updates: DataFrame, key: str, time: str, watermark: str) -> DataFrame:
    """Replayed events count once while they are within the watermark."""
    return updates.withWatermark(time, watermark).dropDuplicatesWithinWatermark([key])


def follow_ups(left: DataFrame, right: DataFrame, minutes: int, watermark: str) -> DataFrame:
    """Stream-stream join: events of ``right`` within some minutes after one of ``left`` by the same user."""
    a = left.select(F.col("user_id"), F.col("ts").alias("t0"), F.col("event_id").alias("first_id")).withWatermark("t0", watermark)
    b = right.select(F.col("user_id").alias("u2"), F.col("ts").alias("t1"), F.col("event_id").alias("next_id")).withWatermark("t1", watermark)
    cond = (F.col("user_id") == F.col("u2")) & (F.col("t1") > F.col("t0")) & (F.col("t1") <= F.col("t0") + F.expr(f"interval {minutes} minutes"))
    return a.join(b, cond).select("first_id", "next_id")


def keep_residuals(updates: DataFrame, threshold: float, timeout_ms: int | None = None) -> DataFrame:
    """Per coordinate: emits the accumulated delta once its magnitude reaches the threshold, else keeps it.

    With ``timeout_ms`` a remainder that gets no update for so long is emitted too; such a query
    never runs out of batches, so it needs a trigger without an end.
    """

    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = state.get[0] if state.exists else 0.0
        if state.hasTimedOut:
            state.remove()
            yield pd.DataFrame({"coord": [key[0]], "sent": [held], "why": ["timeout"]})
            return
        for pdf in frames:
            held += float(pdf["delta"].sum())
        if abs(held) >= threshold:
            yield pd.DataFrame({"coord": [key[0]], "sent": [held], "why": ["threshold"]})
            held = 0.0
        state.update((held,))
        if timeout_ms:
            state.setTimeoutDuration(timeout_ms)

    return updates.select("coord", F.col("delta").cast("double").alias("delta")).groupBy("coord").applyInPandasWithState(
        run, "coord long, sent double, why string", "held double", "update", GroupStateTimeout.ProcessingTimeTimeout if timeout_ms else GroupStateTimeout.NoTimeout
    )


def fold_batches(cells: DataFrame, path: str, checkpoint: str):
    """Starts a query that stores each micro-batch's sketch below its batch id: replays overwrite, never add."""

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.groupBy("row", "bucket").agg(F.sum("cell").alias("cell")).write.mode("overwrite").parquet(f"{path}/batch_id={batch_id}")

    return cells.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def folded(spark, path: str) -> DataFrame:
    return spark.read.parquet(path).groupBy("row", "bucket").agg(F.sum("cell").alias("cell"))
