"""Cross-source track pairs: predicate, score, report."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mediarel.functions.geometry import cosine
from mediarel.operators import intervals

SPEED_RATIO = 1.25
CUT = 0.40
BUCKET_MS = 1000


def candidates(tracks: DataFrame, motion: bool = True, ratio: float = SPEED_RATIO, bucket_ms: int = BUCKET_MS) -> DataFrame:
    """Pairs of tracks of one scene from different sources in canonical order, together in time and (``motion``) alike in motion.

    An equi self-join on (scene, time bucket); the cheap tests stand before the score.
    """
    fields = [c for c in tracks.columns if c != "scene_id"]
    left = tracks.select("scene_id", *[F.col(c).alias(f"l_{c}") for c in fields])
    right = tracks.select("scene_id", *[F.col(c).alias(f"r_{c}") for c in fields])
    pairs = intervals.overlap_join(left, right, ["scene_id"], bucket_ms, ("l_start_ms", "l_end_ms"), ("r_start_ms", "r_end_ms")).where("l_source_id < r_source_id")
    if not motion:
        return pairs
    along = F.col("l_vx") * F.col("r_vx") + F.col("l_vy") * F.col("r_vy") > 0
    fast, slow = (f(F.hypot("l_vx", "l_vy"), F.hypot("r_vx", "r_vy")) for f in (F.greatest, F.least))
    return pairs.where(along & (fast <= ratio * slow + 1e-9))


def scored(pairs: DataFrame, cut: float = CUT) -> DataFrame:
    """Appearance similarity, rounded to 6 so that engines agree, cut below ``cut``."""
    return pairs.withColumn("score", F.round(cosine(F.col("l_emb"), F.col("r_emb")), 6)).where(F.col("score") >= cut)


def to_association(matches: DataFrame) -> DataFrame:
    """Exactly one record a match: (scene_id, vehicle_id, attributes, timeline, match_score); track and join fields go."""
    attribute = lambda name: F.when(F.col(f"l_{name}") == "unknown", F.col(f"r_{name}")).otherwise(F.col(f"l_{name}"))
    seen = lambda s: F.struct(F.col(f"{s}_source_id").alias("source_id"), F.col(f"{s}_start_ms").alias("start_ms"), F.col(f"{s}_end_ms").alias("end_ms"))
    return matches.select(
        "scene_id",
        F.concat_ws(":", "scene_id", "l_track_id", "r_track_id").alias("vehicle_id"),
        F.create_map(F.lit("class"), F.col("l_cls"), F.lit("colour"), attribute("colour"), F.lit("subtype"), F.col("l_subtype")).alias("attributes"),
        F.array(seen("l"), seen("r")).alias("timeline"),
        F.col("score").alias("match_score"),
    )
