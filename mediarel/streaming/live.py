"""Live narration and detections. Every operator has a batch twin; with all input available both give the same rows."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from mediarel.operators.vision import MotionTracker, Trail

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Replay of event files in order of arrival."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def mentions(events: DataFrame) -> DataFrame:
    """What narration would talk about: high purchases and errors."""
    return events.where("event_type IN ('purchase', 'error') AND value >= 120").select(F.col("user_id").alias("source_id"), "ts", "event_id")


def candidate_windows(said: DataFrame, before: str = "20 minutes", after: str = "10 minutes", lateness: str = "1 hour") -> DataFrame:
    """Coalesced padded windows, emitted when the watermark passes their end.

    Windows around two mentions overlap when these are less than ``before + after`` apart, which is a session with that gap:
    state holds one open window a source, not its mentions.
    """
    gap = f"{_minutes(before) + _minutes(after)} minutes"
    sessions = said.withWatermark("ts", lateness).groupBy("source_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n_mentions"))
    start = F.col("w.start") - F.expr(f"INTERVAL {_minutes(before)} MINUTES")
    return sessions.select("source_id", start.alias("start"), (F.col("w.end") - F.expr(f"INTERVAL {_minutes(before)} MINUTES")).alias("end"), "n_mentions")


def _minutes(text: str) -> int:
    return int(text.split()[0])


def mention_counts(events: DataFrame, width: str = "1 hour", slide: str | None = None, lateness: str = "1 hour") -> DataFrame:
    """Tumbling or sliding counts; rows later than the watermark are dropped (Spark counts them in the query's progress)."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    counted = events.withWatermark("ts", lateness).groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("n"))
    return counted.select(F.col("w.start").alias("start"), "event_type", "n")


def once(clips: DataFrame, keys: tuple[str, ...] = ("event_id",), lateness: str = "1 hour") -> DataFrame:
    """Re-delivered clips pass once; state ends with the watermark."""
    return clips.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(list(keys))


def narrated_footage(said: DataFrame, footage: DataFrame, reach: str = "10 minutes", lateness: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: footage rows at most ``reach`` before or after a mention of their source."""
    s = said.select(F.col("source_id"), F.col("ts").alias("said_at"), F.col("event_id").alias("said_id")).withWatermark("said_at", lateness)
    f = footage.select(F.col("user_id").alias("f_source"), F.col("ts").alias("seen_at"), F.col("event_id").alias("seen_id")).withWatermark("seen_at", lateness)
    near = F.expr(f"f_source = source_id AND seen_at >= said_at - INTERVAL {_minutes(reach)} MINUTES AND seen_at <= said_at + INTERVAL {_minutes(reach)} MINUTES")
    return s.join(f, near).select("source_id", "said_id", "seen_id")


TRACK_OUT = "source_id bigint, start_ms bigint, end_ms bigint, first_x double, first_y double, n_det int"
TRACK_STATE = "trails string, waiting string, next_frame int"
_SEEN = ("frame_no", "det_id", "cls", "x", "y", "w", "h")


def track_detections(detections: DataFrame, tracker: MotionTracker | None = None, idle: str = "1 minute", lateness: str = "10 seconds") -> DataFrame:
    """Incremental tracking: a frame is linked once the watermark has passed it, and only open trails stay in state.

    State holds the first and last box of each open trail and the boxes of frames that are not final yet, so it is bounded by what
    moves at a time and by ``lateness``; what comes for a frame that is already linked is late and dropped. A trail leaves when its gap
    is too long or the source is idle. Input rows: source_id, ts, frame_no, det_id, cls, x, y, w, h and others that are ignored.
    """
    tracker = tracker or MotionTracker()

    def advance(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        trails, waiting, following = state.get if state.exists else ("[]", "[]", 0)
        live = [Trail(**t) for t in json.loads(trails)]
        frames: dict[int, list[dict]] = {}
        for ms, d in json.loads(waiting):
            frames.setdefault(d["frame_no"], []).append((ms, d))
        done: list[Trail] = []
        newest = max((ms for rows in frames.values() for ms, _ in rows), default=0)
        if not state.hasTimedOut:
            for batch in batches:
                for r in batch.to_dict("records"):
                    if r["frame_no"] >= following:
                        ms = int(r["ts"].timestamp() * 1000)
                        newest = max(newest, ms)
                        frames.setdefault(int(r["frame_no"]), []).append((ms, {k: r[k].item() if hasattr(r[k], "item") else r[k] for k in _SEEN}))
        mark = state.getCurrentWatermarkMs()
        for frame in sorted(frames):
            if not state.hasTimedOut and max(ms for ms, _ in frames[frame]) >= mark:
                break
            live, ended = tracker.step(live, frame, [d for _, d in frames.pop(frame)], keep=False)
            done += ended
            following = frame + 1
        if state.hasTimedOut:
            done += live
            state.remove()
        else:
            left = [x for rows in frames.values() for x in rows]
            state.update((json.dumps([{"first": t.first, "last": t.last, "n": t.n} for t in live]), json.dumps(left), following))
            state.setTimeoutTimestamp(max(newest, mark) + 60_000 * max(1, _minutes(idle)))
        told = [t for t in done if t.n >= tracker.min_length]
        if told:
            ms = tracker.frame_ms
            rows = [(key[0], t.first["frame_no"] * ms, (t.last["frame_no"] + 1) * ms, t.first["x"], t.first["y"], t.n) for t in told]
            yield pd.DataFrame(rows, columns=["source_id", "start_ms", "end_ms", "first_x", "first_y", "n_det"])

    flow = detections.withWatermark("ts", lateness).groupBy("source_id")
    return flow.applyInPandasWithState(advance, TRACK_OUT, TRACK_STATE, "append", GroupStateTimeout.EventTimeTimeout)


def run_available(df: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Process everything available into a memory table and return it."""
    writer = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    query = writer.start()
    query.awaitTermination()
    return df.sparkSession.table(name)


def late_rows(df: DataFrame, name: str) -> tuple[DataFrame, int]:
    """Run everything available and return the result with the number of rows that came behind the watermark and were dropped."""
    query = df.writeStream.format("memory").queryName(name).outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination()
    dropped = sum(int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"])
    return df.sparkSession.table(name), dropped


def write_each_batch(df: DataFrame, path: str, checkpoint: str):
    """Idempotent sink: a batch overwrites its own folder, so a restarted batch leaves no double rows."""

    def save(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return df.writeStream.foreachBatch(save).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
