"""Intervals, boxes and vectors as codegen expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def overlap_ms(s1: Column, e1: Column, s2: Column, e2: Column) -> Column:
    return F.greatest(F.least(e1, e2) - F.greatest(s1, s2), F.lit(0).cast("bigint"))


def tiou(s1: Column, e1: Column, s2: Column, e2: Column) -> Column:
    """Shared time over joint time; 0 if both intervals are empty."""
    both = overlap_ms(s1, e1, s2, e2)
    joint = (e1 - s1) + (e2 - s2) - both
    return F.when(joint > 0, both / joint).otherwise(F.lit(0.0))


def box_iou(a: tuple[Column, ...], b: tuple[Column, ...]) -> Column:
    """Boxes are (x, y, w, h)."""
    wide = F.greatest(F.least(a[0] + a[2], b[0] + b[2]) - F.greatest(a[0], b[0]), F.lit(0.0))
    high = F.greatest(F.least(a[1] + a[3], b[1] + b[3]) - F.greatest(a[1], b[1]), F.lit(0.0))
    both = wide * high
    joint = a[2] * a[3] + b[2] * b[3] - both
    return F.when(joint > 0, both / joint).otherwise(F.lit(0.0))


def dot(a: Column, b: Column) -> Column:
    product = F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double"))
    return F.aggregate(product, F.lit(0.0), lambda total, x: total + x)


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))


def l2(a: Column, b: Column) -> Column:
    gap = F.zip_with(a, b, lambda x, y: x.cast("double") - y.cast("double"))
    return F.sqrt(F.aggregate(gap, F.lit(0.0), lambda total, x: total + x * x))


def pad_window(start: Column, end: Column, before_ms: int, after_ms: int, duration_ms: Column) -> tuple[Column, Column]:
    """Temporal context around an interval, clamped to its source; the result may be empty."""
    low = F.greatest(start - F.lit(before_ms).cast("bigint"), F.lit(0).cast("bigint"))
    return low, F.least(end + F.lit(after_ms).cast("bigint"), duration_ms)
