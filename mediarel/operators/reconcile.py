"""Clip-level results into one result a source."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from mediarel.operators import intervals

_EVENT_FIELDS = ("start_ms", "end_ms", "conf", "evidence")


def _in_source_time(df: DataFrame, keys: Sequence[str], field: str) -> DataFrame:
    moved = intervals.to_source_time(F.col(field), F.col("_clip.clip_start_ms"))
    return df.select(*keys, F.explode(moved).alias("_e")).select(*keys, *[F.col(f"_e.{f}") for f in _EVENT_FIELDS])


def _collected(df: DataFrame, keys: Sequence[str], field: str) -> DataFrame:
    """Events of a source in a fixed order whatever the order of arrival."""
    return df.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct(*_EVENT_FIELDS))).alias(field))


def chained_points(df: DataFrame, keys: Sequence[str], merge_ms: int) -> DataFrame:
    """Points at most ``merge_ms`` after their predecessor are one event: the most confident stays, then the earliest."""
    order = Window.partitionBy(*keys).orderBy("start_ms", F.desc("conf"))
    opens = F.when(F.col("start_ms") - F.lag("start_ms").over(order) <= merge_ms, 0).otherwise(1)
    runs = df.withColumn("_opens", opens).withColumn("_run", F.sum("_opens").over(order))
    best = F.min(F.struct((-F.col("conf")).alias("c"), F.col("start_ms"), F.col("end_ms"), F.col("conf"), F.col("evidence")))
    return runs.groupBy(*keys, "_run").agg(best.alias("_b")).select(*keys, *[F.col(f"_b.{f}") for f in _EVENT_FIELDS])


def points(merge_ms: int = 2000):
    def fold(df: DataFrame, keys: Sequence[str], field: str) -> DataFrame:
        return _collected(chained_points(_in_source_time(df, keys, field), keys, merge_ms), keys, field)

    return fold


def spans(touching: bool = True):
    """Overlapping spans of one source (and those that touch: cut by a window's edge) are one event."""

    def fold(df: DataFrame, keys: Sequence[str], field: str) -> DataFrame:
        moved = _in_source_time(df, keys, field)
        runs = intervals.islands(moved, keys, touching=not touching)
        merged = runs.groupBy(*keys, "island").agg(F.min("start_ms").alias("start_ms"), F.max("end_ms").alias("end_ms"), F.max("conf").alias("conf"), F.min("evidence").alias("evidence"))
        return _collected(merged, keys, field)

    return fold


def vote(into: str = "label"):
    """Most frequent clip label, the smallest among equals."""

    def fold(df: DataFrame, keys: Sequence[str], field: str) -> DataFrame:
        counted = df.groupBy(*keys, field).agg(F.count("*").alias("_n"))
        return counted.groupBy(*keys).agg(F.min(F.struct((-F.col("_n")).alias("n"), F.col(field).alias("v"))).alias("_b")).select(*keys, F.col("_b.v").alias(into))

    return fold


def any_of(df: DataFrame, keys: Sequence[str], field: str) -> DataFrame:
    return df.groupBy(*keys).agg(F.bool_or(field).alias(field))


def concat(df: DataFrame, keys: Sequence[str], field: str, order: str = "start_ms") -> DataFrame:
    parts = F.transform(F.array_sort(F.collect_list(F.struct(order, field))), lambda p: p[field])
    return df.groupBy(*keys).agg(F.concat_ws(" ", parts).alias(field))
