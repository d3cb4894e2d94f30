"""Coverage, accuracy and cost measures."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mediarel.functions.geometry import tiou
from mediarel.operators import intervals, matching


def f1_of(tp: int, n_pred: int, n_ref: int) -> tuple[float | None, float | None, float | None]:
    """Precision, recall, F1 from counts; undefined values are None."""
    return (tp / n_pred if n_pred else None, tp / n_ref if n_ref else None, 2 * tp / (n_pred + n_ref) if n_pred + n_ref else None)


def reduction(base: float, new: float) -> float:
    return 1 - new / base


def prf(counts: DataFrame) -> DataFrame:
    """Adds precision, recall and f1 to (tp, n_pred, n_ref)."""
    tp, p, r = F.col("tp"), F.col("n_pred"), F.col("n_ref")
    return counts.withColumns(
        {
            "precision": F.when(p > 0, F.round(tp / p, 6)),
            "recall": F.when(r > 0, F.round(tp / r, 6)),
            "f1": F.when(p + r > 0, F.round(2 * tp / (p + r), 6)),
        }
    )


def match_points(pred: DataFrame, ref: DataFrame, tol_ms: int, keys: Sequence[str] = ("source_id",), settle=matching.greedy) -> DataFrame:
    """One-to-one matches of points (keys, ts_ms): smallest error first, then predicted and reference time."""
    p = pred.select(*keys, F.col("ts_ms").alias("pred_ms"))
    r = ref.select(*keys, F.col("ts_ms").alias("ref_ms"))
    pairs = intervals.band_join(p, r, keys, tol_ms, "pred_ms", "ref_ms")
    scored = pairs.select(*keys, "pred_ms", "ref_ms", F.abs(F.col("pred_ms") - F.col("ref_ms")).cast("bigint").alias("error_ms")).withColumn("score", -F.col("error_ms").cast("double"))
    return settle(scored, list(keys), "pred_ms", "ref_ms", "score").drop("score")


def match_spans(pred: DataFrame, ref: DataFrame, theta: float, keys: Sequence[str] = ("source_id",), bucket_ms: int = 60_000, settle=matching.greedy) -> DataFrame:
    """One-to-one matches of spans (keys, start_ms, end_ms) with temporal IoU of ``theta`` or more, largest first."""
    p = pred.select(*keys, "start_ms", "end_ms")
    r = ref.select(*keys, F.col("start_ms").alias("r_start_ms"), F.col("end_ms").alias("r_end_ms"))
    pairs = intervals.overlap_join(p, r, keys, bucket_ms)
    scored = pairs.withColumn("score", tiou(F.col("start_ms"), F.col("end_ms"), F.col("r_start_ms"), F.col("r_end_ms"))).where(F.col("score") >= theta)
    return settle(scored, list(keys), "start_ms", "r_start_ms", "score")


def _curve(scored: DataFrame, preds: DataFrame, ref: DataFrame, thresholds: Sequence[float], keys: Sequence[str], left: str, right: str) -> DataFrame:
    """One-to-one matches of all plans and thresholds in one pass: both are part of the group. ``scored`` has plan, threshold, keys, left, right, score."""
    won = matching.greedy(scored.select("plan", "threshold", *keys, left, right, "score"), ["plan", "threshold", *keys], left, right, "score")
    hits = won.groupBy("plan", "threshold").agg(F.count("*").alias("tp"))
    each = preds.groupBy("plan").agg(F.count("*").alias("n_pred")).withColumn("threshold", F.explode(F.array(*[F.lit(float(t)) for t in thresholds])))
    told = each.join(hits, ["plan", "threshold"], "left").withColumn("tp", F.coalesce("tp", F.lit(0).cast("bigint")))
    return prf(told.crossJoin(F.broadcast(counted(ref, "n_ref")))).select("plan", "threshold", "tp", "n_pred", "n_ref", "precision", "recall", "f1")


def point_curve(preds: DataFrame, ref: DataFrame, tolerances: Sequence[int], keys: Sequence[str] = ("source_id",)) -> DataFrame:
    """plan, threshold, tp, n_pred, n_ref, precision, recall, f1 of predictions (plan, keys, ts_ms) at every tolerance."""
    p, r = preds.select("plan", *keys, F.col("ts_ms").alias("pred_ms")), ref.select(*keys, F.col("ts_ms").alias("ref_ms"))
    pairs = intervals.band_join(p, r, keys, max(tolerances), "pred_ms", "ref_ms").withColumn("score", -F.abs(F.col("pred_ms") - F.col("ref_ms")).cast("double"))
    scored = pairs.withColumn("threshold", F.explode(F.array(*[F.lit(float(t)) for t in tolerances]))).where(-F.col("score") <= F.col("threshold"))
    return _curve(scored, preds, ref, tolerances, keys, "pred_ms", "ref_ms")


def span_curve(preds: DataFrame, ref: DataFrame, thetas: Sequence[float], keys: Sequence[str] = ("source_id",), bucket_ms: int = 60_000) -> DataFrame:
    """The same for spans (plan, keys, start_ms, end_ms) at every temporal IoU."""
    r = ref.select(*keys, F.col("start_ms").alias("r_start_ms"), F.col("end_ms").alias("r_end_ms"))
    pairs = intervals.overlap_join(preds.select("plan", *keys, "start_ms", "end_ms"), r, keys, bucket_ms)
    pairs = pairs.withColumn("score", tiou(F.col("start_ms"), F.col("end_ms"), F.col("r_start_ms"), F.col("r_end_ms")))
    scored = pairs.withColumn("threshold", F.explode(F.array(*[F.lit(float(t)) for t in thetas]))).where(F.col("score") >= F.col("threshold"))
    return _curve(scored, preds, ref, thetas, keys, "start_ms", "r_start_ms")


def counted(df: DataFrame, name: str) -> DataFrame:
    return df.agg(F.count("*").alias(name))


def candidate_recall(refs: DataFrame, windows: DataFrame, keys: Sequence[str], full_cover: bool = True, bucket_ms: int = 600_000) -> DataFrame:
    """Share of references (keys, start_ms, end_ms) inside (or, without ``full_cover``, touched by) a window; a point has end = start.

    References meet windows on time buckets, so a long source with many windows is no single key.
    """
    w = windows.select(*keys, F.col("start_ms").alias("w_start"), F.col("end_ms").alias("w_end"))
    last = F.greatest(F.col("end_ms"), F.col("start_ms") + 1)
    r = refs.groupBy(*keys, "start_ms", last.alias("end_ms")).agg(F.count("*").alias("_times"))
    met = intervals.overlap_join(r, w, keys, bucket_ms, right_span=("w_start", "w_end"))
    if full_cover:
        met = met.where((F.col("w_start") <= F.col("start_ms")) & (F.col("w_end") >= F.col("end_ms")))
    own = [*keys, "start_ms", "end_ms"]
    marked = r.join(met.select(*own).distinct().withColumn("_hit", F.lit(True)), own, "left")
    sums = marked.agg(F.coalesce(F.sum("_times"), F.lit(0)).alias("n_ref"), F.coalesce(F.sum(F.when(F.col("_hit"), F.col("_times"))), F.lit(0)).alias("n_covered"))
    return sums.withColumn("recall", F.when(F.col("n_ref") > 0, F.round(F.col("n_covered") / F.col("n_ref"), 6)))


def selectivity_by_source(windows: DataFrame, sources: DataFrame, keys: Sequence[str] = ("source_id",)) -> DataFrame:
    kept = intervals.union_duration(windows, keys)
    joined = sources.select(*keys, "duration_ms").join(kept, list(keys), "left")
    return joined.select(*keys, F.coalesce("window_ms", F.lit(0).cast("bigint")).alias("window_ms"), F.round(F.coalesce("window_ms", F.lit(0)) / F.col("duration_ms"), 6).alias("selectivity"))


def selectivity(windows: DataFrame, sources: DataFrame, keys: Sequence[str] = ("source_id",)) -> DataFrame:
    """Pooled: union duration of the windows over the duration of all sources."""
    kept = intervals.union_duration(windows, keys).agg(F.coalesce(F.sum("window_ms"), F.lit(0)).cast("bigint").alias("window_ms"))
    whole = sources.agg(F.sum("duration_ms").cast("bigint").alias("source_ms"))
    return kept.crossJoin(F.broadcast(whole)).withColumn("selectivity", F.round(F.col("window_ms") / F.col("source_ms"), 6))


def assoc_score(time_iou: Column, attributes: Column) -> Column:
    return 0.7 * time_iou + 0.3 * attributes


def soft_agreement(left: dict[str, Column], right: dict[str, Column]) -> Column:
    """Mean over attributes of 1 for equal, a half if one side does not know, 0 for different values."""
    each = [
        F.when((left[k] == "unknown") | (right[k] == "unknown") | left[k].isNull() | right[k].isNull(), 0.5).when(left[k] == right[k], 1.0).otherwise(0.0) for k in left
    ]
    total = each[0]
    for e in each[1:]:
        total = total + e
    return total / len(each)
