"""Streams: windows, sessions, and clips collapsed or measured as their frames arrive.

Event times are timestamps with zone UTC; the given tables' times without zone are cast first, as watermarks need.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

SESSION_GAP = 12 * 3600


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """A stream of event files as they arrive in a folder."""
    schema = spark.read.parquet(path).schema
    ev = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return ev.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(ev: DataFrame, width: str = "1 hour", late: str = "1 hour", streaming: bool = True) -> DataFrame:
    ev = ev.withWatermark("ts", late) if streaming else ev
    return ev.groupBy(F.window("ts", width).alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))


def sliding(ev: DataFrame, width: str = "6 hours", step: str = "1 hour", late: str = "1 hour", streaming: bool = True) -> DataFrame:
    ev = ev.withWatermark("ts", late) if streaming else ev
    return ev.groupBy(F.window("ts", width, step).alias("w")).agg(F.count(F.lit(1)).alias("n"))


def sessions(ev: DataFrame, gap: str = "12 hours", late: str = "1 hour", streaming: bool = True) -> DataFrame:
    """user_id, w (start and end), n. Never filter the bounds of this result before it is stored: the optimiser would push
    the filter below the merge of sessions and cut them."""
    ev = ev.withWatermark("ts", late) if streaming else ev
    return ev.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"))


def sessions_batch(ev: DataFrame, time: str = "e", gap: float = SESSION_GAP) -> DataFrame:
    """The same from a lag and a running sum: user_id, s0, s1 (first and last event), n. Its bounds can be filtered."""
    w = Window.partitionBy("user_id").orderBy(time, "event_id")
    starts = F.coalesce((F.col(time) - F.lag(time).over(w) >= gap).cast("int"), F.lit(1))
    marked = ev.withColumn("starts", starts).withColumn("session", F.sum("starts").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return marked.groupBy("user_id", "session").agg(F.min(time).alias("s0"), F.max(time).alias("s1"), F.count(F.lit(1)).alias("n")).drop("session")


def unique_frames(ev: DataFrame, late: str = "1 hour") -> DataFrame:
    return ev.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def with_context(ev: DataFrame, static: DataFrame, key: str) -> DataFrame:
    """A stream joined with a table, as frames with their user's rules: the table is read anew in every batch."""
    return ev.join(static, key, "left")


def speech_with_faces(speech: DataFrame, faces: DataFrame, late: str = "1 hour", apart: str = "10 minutes") -> DataFrame:
    """Two streams (user_id, ts, ...) and (user_id, face_ts, ...): pairs of one user at most ``apart`` in time.

    Both have watermarks and the times bound each other, so that rows leave the state when none can meet them any more.
    """
    a, b = speech.withWatermark("ts", late), faces.withWatermark("face_ts", late).withColumnRenamed("user_id", "face_user")
    near = f"user_id = face_user AND face_ts BETWEEN ts - INTERVAL {apart} AND ts + INTERVAL {apart}"
    return a.join(b, F.expr(near)).drop("face_user")


def incremental_collapse(frames: DataFrame, blank: str = "_", late: str = "10 minutes") -> DataFrame:
    """A stream of frames (utt, t, sym [, ts]) -> (utt, t, label): each frame that adds a label, as it arrives.

    State: a clip's last symbol. Frames of a batch are put in order; a frame that comes after later ones of an earlier
    batch is dropped, as the state has moved on. With event times a clip's state goes when the watermark has passed its
    last frame by 30 minutes; without them it stays as long as the stream.
    """
    timed = "ts" in frames.columns

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        last, seen = state.get if state.exists else (blank, -1)
        out, parts, latest = [], [], 0
        for b in batches:  # a clip is 12 seconds at most: its frames are few, and only two columns are kept
            parts.append(b[["t", "sym"]])
            if timed:
                latest = max(latest, int(b["ts"].max().timestamp() * 1000))
        rows = pd.concat(parts).sort_values("t")
        for t, sym in zip(rows["t"], rows["sym"]):
            if t <= seen:
                continue
            if sym != blank and sym != last:
                out.append((key[0], int(t), sym))
            last, seen = sym, int(t)
        state.update((last, seen))
        if timed:
            state.setTimeoutTimestamp(max(latest, state.getCurrentWatermarkMs()) + 30 * 60_000)
        yield pd.DataFrame(out, columns=["utt", "t", "label"])

    rows = frames.withWatermark("ts", late) if timed else frames
    limit = GroupStateTimeout.EventTimeTimeout if timed else GroupStateTimeout.NoTimeout
    return rows.groupBy("utt").applyInPandasWithState(step, "utt string, t int, label string", "last string, seen int", "append", limit)


def running_openness(frames: DataFrame, idle_ms: int = 24 * 3_600_000) -> DataFrame:
    """A stream of (user_id, value, k) -> (user_id, n, sd): the spread of normalised openness so far, by Welford's update.

    A user who sends nothing for ``idle_ms`` is forgotten.
    """

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        n, mean, m2 = state.get if state.exists else (0, 0.0, 0.0)
        for b in batches:
            for x in b["value"] / (100 + b["k"]):
                n += 1
                delta = x - mean
                mean += delta / n
                m2 += delta * (x - mean)
        state.update((n, mean, m2))
        state.setTimeoutDuration(idle_ms)
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "sd": [(m2 / n) ** 0.5 if n else 0.0]})

    return frames.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, sd double", "n long, mean double, m2 double", "update", GroupStateTimeout.ProcessingTimeTimeout)


def mine(ev: DataFrame, static: DataFrame, key: str = "user_id", cap: int = 30) -> DataFrame:
    """A stream of frames through the cheap rules end to end: duplicates out, static limits joined, frames that pass counted by hour."""
    seen = unique_frames(ev)
    kept = with_context(seen, static, key).where("abs(value - 50) / 5 <= coalesce(max_yaw, 30)")
    return kept.groupBy(F.window("ts", "1 hour").alias("w"), key).agg(F.count(F.lit(1)).alias("n"))


def store_batches(stream: DataFrame, path: str, checkpoint: str, split: str = "split"):
    """A query that stores each batch of a stream by split, once: a batch that is run again replaces what it has written."""

    def store(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").partitionBy(split).parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(store).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
