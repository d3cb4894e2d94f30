"""SQL names of the engine: scalar functions as SQL expressions, set functions as table functions."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from mediarel.functions import udfs
from mediarel.operators.vision import MotionTracker

#: Scalar functions as SQL bodies: they inline into the calling plan and stay in generated code.
SCALARS = {
    "tiou": (
        "s1 BIGINT, e1 BIGINT, s2 BIGINT, e2 BIGINT",
        "DOUBLE",
        "CASE WHEN (e1 - s1) + (e2 - s2) - greatest(least(e1, e2) - greatest(s1, s2), 0) > 0 THEN greatest(least(e1, e2) - greatest(s1, s2), 0) / ((e1 - s1) + (e2 - s2) - greatest(least(e1, e2) - greatest(s1, s2), 0)) ELSE 0D END",
    ),
    "pad_start": ("s BIGINT, before_ms BIGINT", "BIGINT", "greatest(s - before_ms, 0)"),
    "pad_end": ("e BIGINT, after_ms BIGINT, duration_ms BIGINT", "BIGINT", "least(e + after_ms, duration_ms)"),
    "pad_window": (
        "s BIGINT, e BIGINT, before_ms BIGINT, after_ms BIGINT, duration_ms BIGINT",
        "STRUCT<start_ms: BIGINT, end_ms: BIGINT>",
        "named_struct('start_ms', greatest(s - before_ms, 0L), 'end_ms', least(e + after_ms, duration_ms))",
    ),
    "box_iou": (
        "ax DOUBLE, ay DOUBLE, aw DOUBLE, ah DOUBLE, bx DOUBLE, by DOUBLE, bw DOUBLE, bh DOUBLE",
        "DOUBLE",
        "CASE WHEN aw * ah + bw * bh - greatest(least(ax + aw, bx + bw) - greatest(ax, bx), 0D) * greatest(least(ay + ah, by + bh) - greatest(ay, by), 0D) > 0 "
        "THEN greatest(least(ax + aw, bx + bw) - greatest(ax, bx), 0D) * greatest(least(ay + ah, by + bh) - greatest(ay, by), 0D) "
        "/ (aw * ah + bw * bh - greatest(least(ax + aw, bx + bw) - greatest(ax, bx), 0D) * greatest(least(ay + ah, by + bh) - greatest(ay, by), 0D)) ELSE 0D END",
    ),
    "cosine_sim": (
        "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>",
        "DOUBLE",
        "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (t, x) -> t + x) / sqrt(aggregate(a, 0D, (t, x) -> t + x * x) * aggregate(b, 0D, (t, x) -> t + x * x))",
    ),
}


@F.udtf(returnType="source_id bigint, start_ms bigint, end_ms bigint")
class CoalesceSpans:
    """``coalesce_spans(TABLE(t) PARTITION BY source_id ORDER BY start_ms)``: merged spans of one source, streamed in order."""

    def __init__(self):
        self.open = None

    def eval(self, row):
        start, end = row["start_ms"], row["end_ms"]
        if self.open and start < self.open[2]:
            self.open[2] = max(self.open[2], end)
            return
        if self.open:
            yield tuple(self.open)
        self.open = [row["source_id"], start, end]

    def terminate(self):
        if self.open:
            yield tuple(self.open)


@F.udtf(returnType="source_id bigint, l bigint, r bigint, score double")
class MatchOneToOne:
    """``match_one_to_one(TABLE(t) PARTITION BY source_id ORDER BY (score DESC, l, r))``: greedy matching of one group."""

    def __init__(self):
        self.left, self.right = set(), set()

    def eval(self, row):
        if row["l"] not in self.left and row["r"] not in self.right:
            self.left.add(row["l"])
            self.right.add(row["r"])
            yield row["source_id"], row["l"], row["r"], row["score"]


@F.udtf(returnType="source_id bigint, track_no bigint, start_ms bigint, end_ms bigint, n_det bigint")
class TrackBoxes:
    """``track_boxes(TABLE(t) PARTITION BY source_id ORDER BY (frame_no, det_id))``: tracks of one source, linked frame by frame."""

    def __init__(self):
        self.tracker, self.live, self.frame, self.found, self.source, self.no = MotionTracker(), [], None, [], None, 0

    def eval(self, row):
        if self.frame is not None and row["frame_no"] != self.frame:
            yield from self._linked()
        self.source, self.frame = row["source_id"], row["frame_no"]
        self.found.append({k: row[k] for k in ("frame_no", "det_id", "cls", "x", "y", "w", "h")})

    def _linked(self):
        self.live, ended = self.tracker.step(self.live, self.frame, self.found, keep=False)
        self.found = []
        yield from self._told(ended)

    def _told(self, trails):
        for t in trails:
            if t.n >= self.tracker.min_length:
                yield self.source, self.no, t.first["frame_no"] * self.tracker.frame_ms, (t.last["frame_no"] + 1) * self.tracker.frame_ms, t.n
                self.no += 1

    def terminate(self):
        if self.frame is not None:
            yield from self._linked()
            yield from self._told(self.live)


@F.arrow_udtf(returnType="source_id bigint, union_ms bigint")
class UnionSpans:
    """``union_spans(TABLE(t) PARTITION BY source_id ORDER BY start_ms)``: length of a source's union, on Arrow batches."""

    def __init__(self):
        self.source, self.total, self.reach = None, 0, None

    def eval(self, rows: pa.RecordBatch):
        start, end = (np.asarray(rows.column(rows.schema.get_field_index(c)), dtype=np.int64) for c in ("start_ms", "end_ms"))
        if len(start):
            self.source = rows.column(rows.schema.get_field_index("source_id"))[0].as_py()
            before = np.maximum.accumulate(np.concatenate(([self.reach if self.reach is not None else start[0]], end)))
            self.total += int(np.maximum(end - np.maximum(start, before[:-1]), 0).sum())
            self.reach = int(before[-1])
        return iter(())

    def terminate(self):
        if self.source is not None:
            yield pa.table({"source_id": pa.array([self.source], pa.int64()), "union_ms": pa.array([self.total], pa.int64())})


def register(spark: SparkSession) -> None:
    for name, (arguments, returns, body) in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({arguments}) RETURNS {returns} RETURN {body}")
    spark.udtf.register("coalesce_spans", CoalesceSpans)
    spark.udtf.register("match_one_to_one", MatchOneToOne)
    spark.udtf.register("track_boxes", TrackBoxes)
    spark.udtf.register("union_spans", UnionSpans)
    for name in ("cosine_batch", "box_iou_batch", "vector_mean", "union_ms"):
        spark.udf.register(name, getattr(udfs, name))
