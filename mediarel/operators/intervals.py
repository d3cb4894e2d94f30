"""Set-level interval operators and interval joins."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def islands(df: DataFrame, within: Sequence[str], start: str = "start_ms", end: str = "end_ms", touching: bool = False, into: str = "island") -> DataFrame:
    """Numbers runs of overlapping intervals of a group. One shuffle by ``within``; windows spill."""
    order = Window.partitionBy(*within).orderBy(start, end)
    reach = F.max(end).over(order.rowsBetween(Window.unboundedPreceding, -1))
    apart = F.col(start) > reach if touching else F.col(start) >= reach
    opens = F.when(reach.isNull() | apart, 1).otherwise(0)
    return df.withColumn("_opens", opens).withColumn(into, F.sum("_opens").over(order.rowsBetween(Window.unboundedPreceding, 0))).drop("_opens")


def coalesce(df: DataFrame, within: Sequence[str], start: str = "start_ms", end: str = "end_ms", touching: bool = False) -> DataFrame:
    """Merge overlapping intervals of a group: (within, start, end, window_no from 0). Half-open intervals that touch stay apart by default."""
    merged = islands(df, within, start, end, touching).groupBy(*within, "island").agg(F.min(start).alias(start), F.max(end).alias(end))
    return merged.select(*within, (F.col("island") - 1).cast("bigint").alias("window_no"), start, end)


def coalesce_two_level(df: DataFrame, within: Sequence[str], bucket_ms: int, start: str = "start_ms", end: str = "end_ms") -> DataFrame:
    """The same for very long sources: first within time buckets, so no task orders a whole source, then across buckets.

    Intervals are cut at bucket borders; pieces of one bucket merge there, and what touches across a border and came from
    one interval joins again. The second step sees merged pieces only.
    """
    first = F.expr(f"`{start}` div {bucket_ms}")
    last = F.expr(f"(`{end}` - 1) div {bucket_ms}")
    cut = df.where(F.col(end) > F.col(start)).select(*within, start, end, F.explode(F.sequence(first, last)).alias("_bucket"))
    low, high = F.col("_bucket") * bucket_ms, (F.col("_bucket") + 1) * bucket_ms
    pieces = cut.select(
        *within, "_bucket", F.greatest(F.col(start), low).alias(start), F.least(F.col(end), high).alias(end), (F.col(start) < low).alias("_from_left")
    )
    runs = islands(pieces, [*within, "_bucket"], start, end).groupBy(*within, "_bucket", "island").agg(
        F.min(start).alias(start), F.max(end).alias(end), F.max("_from_left").alias("_from_left")
    )
    order = Window.partitionBy(*within).orderBy(start)
    joined = F.col("_from_left") & (F.lag(end).over(order) == F.col(start))
    numbered = runs.withColumn("_opens", F.when(F.coalesce(joined, F.lit(False)), 0).otherwise(1)).withColumn("island", F.sum("_opens").over(order))
    merged = numbered.groupBy(*within, "island").agg(F.min(start).alias(start), F.max(end).alias(end))
    return merged.select(*within, (F.col("island") - 1).cast("bigint").alias("window_no"), start, end)


def union_duration(df: DataFrame, within: Sequence[str], start: str = "start_ms", end: str = "end_ms") -> DataFrame:
    return coalesce(df, within, start, end).groupBy(*within).agg(F.sum(F.col(end) - F.col(start)).cast("bigint").alias("window_ms"))


def to_source_time(events: Column, clip_start: Column) -> Column:
    """Clip-relative events mapped back to the source's clock."""
    return F.transform(events, lambda e: e.withField("start_ms", e["start_ms"] + clip_start).withField("end_ms", e["end_ms"] + clip_start))


def overlap_join(left: DataFrame, right: DataFrame, on: Sequence[str], bucket_ms: int, left_span: tuple[str, str] = ("start_ms", "end_ms"), right_span: tuple[str, str] = ("r_start_ms", "r_end_ms")) -> DataFrame:
    """Pairs of one key whose half-open intervals overlap: an equi join on (key, time bucket), each pair from its first common bucket only."""

    def dealt(df: DataFrame, span: tuple[str, str], first: str) -> DataFrame:
        return df.where(F.col(span[1]) > F.col(span[0])).withColumn(first, F.expr(f"`{span[0]}` div {bucket_ms}")).withColumn("_bucket", F.explode(F.sequence(F.col(first), F.expr(f"(`{span[1]}` - 1) div {bucket_ms}"))))

    joined = dealt(left, left_span, "_first_l").join(dealt(right, right_span, "_first_r"), [*on, "_bucket"])
    own = F.col("_bucket") == F.greatest("_first_l", "_first_r")
    overlap = (F.col(left_span[0]) < F.col(right_span[1])) & (F.col(right_span[0]) < F.col(left_span[1]))
    return joined.where(own & overlap).drop("_bucket", "_first_l", "_first_r")


def point_join(points: DataFrame, windows: DataFrame, on: Sequence[str], bucket_ms: int, at: str = "ts_ms", span: tuple[str, str] = ("start_ms", "end_ms")) -> DataFrame:
    """Points inside half-open windows of one key: the point has one bucket, so no pair repeats."""
    dealt = windows.where(F.col(span[1]) > F.col(span[0])).withColumn("_bucket", F.explode(F.sequence(F.expr(f"`{span[0]}` div {bucket_ms}"), F.expr(f"(`{span[1]}` - 1) div {bucket_ms}"))))
    joined = points.withColumn("_bucket", F.expr(f"`{at}` div {bucket_ms}")).join(dealt, [*on, "_bucket"])
    return joined.where((F.col(at) >= F.col(span[0])) & (F.col(at) < F.col(span[1]))).drop("_bucket")


def band_join(left: DataFrame, right: DataFrame, on: Sequence[str], tol: int, left_at: str, right_at: str) -> DataFrame:
    """Pairs of one key at most ``tol`` apart: buckets as wide as the tolerance, the left side visits three."""
    width = max(tol, 1)
    near = left.withColumn("_bucket", F.explode(F.array(*[F.floor(F.col(left_at) / width) + k for k in (-1, 0, 1)])))
    joined = near.join(right.withColumn("_bucket", F.floor(F.col(right_at) / width)), [*on, "_bucket"])
    return joined.where(F.abs(F.col(left_at) - F.col(right_at)) <= tol).drop("_bucket")
