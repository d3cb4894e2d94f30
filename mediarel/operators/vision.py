"""Boxes: suppression, motion tracking, chunked tracking with stitching."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

TRACK_FIELDS = (
    "track_id bigint, start_ms bigint, end_ms bigint, first_frame int, last_frame int, first_x double, first_y double, last_x double, last_y double, "
    "w double, h double, vx double, vy double, n_det int, cls string, colour string, subtype string, emb array<double>"
)


def iou_matrix(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """IoU of (x, y, w, h) rows with (x, y, w, h) rows."""
    low = np.maximum(a[:, None, :2], b[None, :, :2])
    high = np.minimum(a[:, None, :2] + a[:, None, 2:], b[None, :, :2] + b[None, :, 2:])
    inter = np.prod(np.clip(high - low, 0, None), axis=2)
    return inter / np.maximum(a[:, 2:].prod(axis=1)[:, None] + b[:, 2:].prod(axis=1)[None, :] - inter, 1e-12)


def suppress(boxes: Sequence[dict], iou: float = 0.5, per_class: bool = True) -> list[dict]:
    """Of overlapping boxes of one frame (and class) the most confident stays; ties go to the smaller det_id."""
    kept: list[dict] = []
    for b in sorted(boxes, key=lambda b: (-b["conf"], b["det_id"])):
        rivals = [k for k in kept if not per_class or k["cls"] == b["cls"]]
        if not rivals or iou_matrix(_boxes([b]), _boxes(rivals)).max() <= iou:
            kept.append(b)
    return sorted(kept, key=lambda b: b["det_id"])


def _boxes(rows: Sequence[dict]) -> np.ndarray:
    return np.array([[r["x"], r["y"], r["w"], r["h"]] for r in rows], dtype=float)


@dataclass
class Trail:
    """Detections linked so far: the first and the last of them, how many, and all of them where ``dets`` is a list."""

    first: dict
    last: dict
    n: int = 1
    dets: list[dict] | None = None

    def at(self, frame: int) -> list[float]:
        """Box expected in a frame: constant velocity over the trail so far."""
        last, first = self.last, self.first
        steps = last["frame_no"] - first["frame_no"]
        vx, vy = ((last["x"] - first["x"]) / steps, (last["y"] - first["y"]) / steps) if steps else (0.0, 0.0)
        ahead = frame - last["frame_no"]
        return [last["x"] + vx * ahead, last["y"] + vy * ahead, last["w"], last["h"]]

    def add(self, det: dict) -> None:
        self.last, self.n = det, self.n + 1
        if self.dets is not None:
            self.dets.append(det)


@dataclass(frozen=True)
class MotionTracker:
    """Links detections of one source over frames: predicted boxes, greedy by IoU, short gaps bridged."""

    iou: float = 0.3
    max_gap: int = 2
    min_length: int = 3
    frame_ms: int = 100

    def step(self, live: list[Trail], frame: int, found: Sequence[dict], keep: bool = True) -> tuple[list[Trail], list[Trail]]:
        """(trails still open, trails that ended) after the detections of one more frame; it needs nothing but the open trails."""
        ended = [t for t in live if frame - t.last["frame_no"] > self.max_gap + 1]
        live = [t for t in live if frame - t.last["frame_no"] <= self.max_gap + 1]
        found = sorted(found, key=lambda d: d["det_id"])
        taken_t: set[int] = set()
        taken_d: set[int] = set()
        if live:
            scores = iou_matrix(np.array([t.at(frame) for t in live]), _boxes(found))
            for i, j in sorted(zip(*np.nonzero(scores >= self.iou), strict=True), key=lambda p: (-scores[p], p)):
                if i not in taken_t and j not in taken_d and live[i].last["cls"] == found[j]["cls"]:
                    live[i].add(found[j])
                    taken_t.add(i)
                    taken_d.add(j)
        return live + [Trail(d, d, 1, [d] if keep else None) for j, d in enumerate(found) if j not in taken_d], ended

    def trails(self, dets: Sequence[dict]) -> list[list[dict]]:
        live: list[Trail] = []
        done: list[Trail] = []
        by_frame: dict[int, list[dict]] = {}
        for d in dets:
            by_frame.setdefault(d["frame_no"], []).append(d)
        for frame in sorted(by_frame):
            live, ended = self.step(live, frame, by_frame[frame])
            done += ended
        return [t.dets for t in done + live]

    def tracks(self, dets: Sequence[dict], min_length: int | None = None) -> list[dict]:
        least = self.min_length if min_length is None else min_length
        rows = []
        for trail in self.trails(dets):
            if len(trail) < least:
                continue
            first, last = trail[0], trail[-1]
            steps = max(last["frame_no"] - first["frame_no"], 1)
            known = [d["colour"] for d in trail]
            rows.append(
                {
                    "start_ms": first["frame_no"] * self.frame_ms, "end_ms": (last["frame_no"] + 1) * self.frame_ms,
                    "first_frame": first["frame_no"], "last_frame": last["frame_no"],
                    "first_x": first["x"], "first_y": first["y"], "last_x": last["x"], "last_y": last["y"], "w": last["w"], "h": last["h"],
                    "vx": (last["x"] - first["x"]) / steps, "vy": (last["y"] - first["y"]) / steps, "n_det": len(trail),
                    "cls": first["cls"], "colour": max(sorted(set(known)), key=known.count), "subtype": first["subtype"],
                    "emb": np.mean([d["emb"] for d in trail], axis=0).tolist(),
                }
            )
        rows.sort(key=lambda r: (r["first_frame"], r["first_x"], r["first_y"]))
        return [{"track_id": k, **r} for k, r in enumerate(rows)]


def suppress_column(df: DataFrame, field_name: str, iou: float = 0.5) -> DataFrame:
    """Suppression of every frame of the detection collections, in Arrow batches."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            for dets in batch[field_name]:
                by_frame: dict[int, list[dict]] = {}
                for d in dets:
                    by_frame.setdefault(d["frame_no"], []).append(dict(d))
                out.append([d for f in sorted(by_frame) for d in suppress(by_frame[f], iou)])
            batch[field_name] = out
            yield batch

    return df.mapInPandas(run, df.schema)


def track_column(df: DataFrame, field_name: str, into: str, tracker: MotionTracker | None = None) -> DataFrame:
    """One collection of tracks a source; the detections are dropped, only means travel on."""
    tracker = tracker or MotionTracker()
    kept = [f for f in df.schema.fields if f.name != field_name]
    element = T.StructType.fromDDL(TRACK_FIELDS)
    schema = T.StructType([*kept, T.StructField(into, T.ArrayType(element))])

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            made = batch[[f.name for f in kept]].copy()
            made[into] = [tracker.tracks(list(dets)) for dets in batch[field_name]]
            yield made

    return df.mapInPandas(run, schema)


def stitch(pieces: DataFrame, tracker: MotionTracker | None = None) -> DataFrame:
    """Tracks of neighbouring chunks of a source that continue each other: (source_id, left, right) links.

    A long feed is tracked in chunks so that no task holds a whole day. A piece that ends near a chunk's end links to
    the piece of the next chunk whose first box fits its motion best; links close over ``matching.connected_groups``.
    Input: (source_id, chunk, track_id) with the track fields.
    """
    tracker = tracker or MotionTracker()
    left = pieces.select("source_id", "chunk", *[F.col(c).alias(f"l_{c}") for c in ("track_id", "last_frame", "last_x", "last_y", "w", "h", "vx", "vy", "cls")])
    right = pieces.select("source_id", (F.col("chunk") - 1).alias("chunk"), *[F.col(c).alias(f"r_{c}") for c in ("track_id", "first_frame", "first_x", "first_y", "w", "h", "cls")])
    gap = F.col("r_first_frame") - F.col("l_last_frame")
    near = left.join(right, ["source_id", "chunk"]).where((gap >= 1) & (gap <= tracker.max_gap + 1) & (F.col("l_cls") == F.col("r_cls")))
    from mediarel.functions.geometry import box_iou
    from mediarel.operators.matching import greedy

    expected = (F.col("l_last_x") + F.col("l_vx") * gap, F.col("l_last_y") + F.col("l_vy") * gap, F.col("l_w"), F.col("l_h"))
    scored = near.withColumn("score", box_iou(expected, (F.col("r_first_x"), F.col("r_first_y"), F.col("r_w"), F.col("r_h")))).where(F.col("score") >= tracker.iou)
    links = greedy(scored.select("source_id", "chunk", "l_track_id", "r_track_id", "score"), ["source_id", "chunk"], "l_track_id", "r_track_id", "score")
    return links.select("source_id", "chunk", "l_track_id", "r_track_id")
