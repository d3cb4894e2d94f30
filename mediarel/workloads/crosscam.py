"""Vehicles across two cameras: one-shot association and the staged pipeline, with coverage and association measures.

Scenes are closed-form fixtures over ``embeddings`` and ``part``: 20 vehicles, two cameras, 50 frames. The pipeline
sees boxes and crops only; the vehicle number joins back in measures alone, through positions.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mediarel import measures
from mediarel.functions.geometry import tiou
from mediarel.operators import matching, pairing, vision
from mediarel.plans.frame import MediaFrame
from mediarel.plans.rules import DecomposeAssociation
from mediarel.schema import media_ref
from mediarel.sources.stored import barrier

CUTS = (0.2, 0.3, 0.4, 0.5, 0.6)


def _cameras(n: int):
    return F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("camera")


def vehicles(spark: SparkSession, sf_dir: str, cameras: int = 2) -> DataFrame:
    """(k, camera, scene, source, frames, attributes): what is really there."""
    vectors, part = spark.read.parquet(f"{sf_dir}/embeddings.parquet"), spark.read.parquet(f"{sf_dir}/part.parquet")
    n_parts = part.count()
    base = vectors.select(F.col("vec_id").alias("k"), _cameras(cameras))
    base = base.where("NOT (camera = 0 AND k % 11 = 0) AND NOT (camera = 1 AND k % 7 = 0) AND NOT (camera = 2 AND k % 13 = 0)")
    base = base.selectExpr(
        "k", "camera", "k div 20 AS scene_id", f"(k div 20) * {cameras} + camera AS source_id", "int((k * 3) % 20 + camera * (k % 5)) AS first_frame",
        "IF(k % 2 = 1, -1, 1) * (8 + k % 5) AS speed", f"k % {n_parts} AS p_partkey",
    )
    named = part.select("p_partkey", F.col("p_type").alias("cls"), F.split("p_name", " ")[0].alias("colour"), F.col("p_brand").alias("subtype"))
    return base.join(named, "p_partkey").drop("p_partkey")


def crops(spark: SparkSession, sf_dir: str, cameras: int = 2) -> DataFrame:
    """(crop, emb): the stand-in embedder's answer for a crop, a vehicle's vector with another mixed in."""
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").alias("k"), F.col("embedding").cast("array<double>").alias("v"))
    n = vectors.count()
    each = vectors.select("k", "v", _cameras(cameras)).withColumn("j", F.expr(f"(k * 13 + 7 * camera + 5) % {n}"))
    other = vectors.select(F.col("k").alias("j"), F.col("v").alias("o"))
    weight = F.expr("IF(k % 9 = 0 AND camera = 1, 3.0D, 0.5D)")
    return each.join(other, "j").select((F.col("k") * cameras + F.col("camera")).alias("crop"), F.zip_with("v", F.transform("o", lambda x: x * weight), lambda a, b: a + b).alias("emb"))


def sources(spark: SparkSession, sf_dir: str, cameras: int = 2) -> DataFrame:
    scenes = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.expr("vec_id div 20").alias("scene_id")).distinct()
    each = scenes.select("scene_id", _cameras(cameras)).withColumn("source_id", F.col("scene_id") * cameras + F.col("camera"))
    return each.withColumn("duration_ms", F.lit(5000).cast("bigint")).withColumn("v", media_ref(F.col("source_id"), F.col("duration_ms")))


def boxes(spark: SparkSession, sf_dir: str, cameras: int = 2) -> DataFrame:
    """Raw detector output in flat form: main boxes with drop-outs, and weaker duplicates beside them."""
    seen = vehicles(spark, sf_dir, cameras).withColumn("frame_no", F.explode(F.sequence(F.col("first_frame"), F.col("first_frame") + 24))).where("(k * 3 + frame_no) % 10 != 0")
    colour = F.expr("IF(camera = 1 AND k % 5 = 2, 'unknown', colour)")
    extra = F.explode(F.expr("IF((k + frame_no) % 6 = 0, array(0, 4), array(0))")).alias("off")
    placed = seen.select("k", "camera", "source_id", "frame_no", "speed", "cls", colour.alias("colour"), "subtype", extra)
    flat = placed.selectExpr(
        "source_id", "frame_no", "bigint(frame_no * 100) AS ts_ms", "cls", "colour", "subtype", "double(700 + speed * frame_no + 300 * camera + off) AS x", "double(60 * (k % 20)) AS y",
        "50.0D AS w", "40.0D AS h", "IF(off = 0, 0.9D, 0.6D) AS conf", f"k * {cameras} + camera AS crop",
    )
    return flat.withColumn("det_id", F.expr("bigint(row_number() OVER (PARTITION BY source_id ORDER BY frame_no, x, y))"))


_FIELDS = ("det_id", "frame_no", "ts_ms", "cls", "colour", "subtype", "x", "y", "w", "h", "conf", "crop")


def detector(spark: SparkSession, sf_dir: str, cameras: int = 2):
    def detect(df: DataFrame, on: str, classes: tuple[str, ...], into: str) -> DataFrame:
        found = boxes(spark, sf_dir, cameras)
        found = found.where(F.col("cls").isin(*classes)) if classes else found
        lists = found.groupBy("source_id").agg(F.array_sort(F.collect_list(F.struct(*_FIELDS))).alias(into))
        return df.join(lists, "source_id")

    return detect


def refiner(spark: SparkSession, sf_dir: str, cameras: int = 2):
    """Suppress, then embed what is left."""

    def refine(df: DataFrame, on: str, into: str) -> DataFrame:
        kept = vision.suppress_column(df.drop("v"), on)
        flat = kept.select("scene_id", "camera", "source_id", F.explode(on).alias("d")).select("scene_id", "camera", "source_id", "d.*")
        with_vector = flat.join(crops(spark, sf_dir, cameras), "crop").drop("crop")
        return with_vector.groupBy("scene_id", "camera", "source_id").agg(F.array_sort(F.collect_list(F.struct(*[f for f in _FIELDS if f != "crop"], "emb"))).alias(into))

    return refine


def _pair(motion: bool = True, cut: float = pairing.CUT):
    def pair(tracks: DataFrame) -> DataFrame:
        flat = tracks.select("scene_id", "source_id", "_t.*")
        found = pairing.scored(pairing.candidates(flat, motion), cut)
        return found.withColumns({"left_source": F.col("l_source_id"), "right_source": F.col("r_source_id")})

    return pair


def _settle(df: DataFrame, within: list[str]) -> DataFrame:
    narrow = df.select(*within, "l_track_id", "r_track_id", "score")
    won = matching.greedy(narrow, within, "l_track_id", "r_track_id", "score").drop("score")
    return df.join(won, [*within, "l_track_id", "r_track_id"])




def associator(spark: SparkSession, sf_dir: str):
    """Simulated one-shot model: one call a scene; precise, but it reports every fifth vehicle and cuts timelines short."""
    truth = vehicles(spark, sf_dir).select("scene_id", "source_id", "k", "camera", "first_frame", "cls", "colour", "subtype")

    def run(df: DataFrame, keys: list[str]) -> DataFrame:
        shown = df.select("scene_id", "source_id").join(truth, ["scene_id", "source_id"]).where("k % 5 = 0")
        kind = "scene_id bigint, A array<struct<vehicle_id:string,attributes:map<string,string>,timeline:array<struct<source_id:bigint,start_ms:bigint,end_ms:bigint>>,match_score:double>>"

        def call(group):
            import pandas as pd

            found = []
            for k, rows in group.groupby("k"):
                if len(rows) == 2:
                    rows = rows.sort_values("source_id")
                    first = rows.iloc[0]
                    line = [{"source_id": int(s), "start_ms": int(f) * 100, "end_ms": int(f) * 100 + 1800} for s, f in zip(rows["source_id"], rows["first_frame"], strict=True)]
                    found.append({"vehicle_id": f"{first['scene_id']}:{k}", "attributes": {"class": first["cls"], "colour": first["colour"], "subtype": first["subtype"]}, "timeline": line, "match_score": 1.0})
            return pd.DataFrame({"scene_id": [int(group["scene_id"].iloc[0])], "A": [found]})

        return shown.groupBy(*keys).applyInPandas(call, kind)

    run.associates = True
    return run


def one_shot_plan(spark: SparkSession, sf_dir: str, cameras: int = 2) -> MediaFrame:
    return MediaFrame.of(sources(spark, sf_dir, cameras), "feeds").fold(["scene_id"], associator(spark, sf_dir)).unnest("A")


def staged_plan(spark: SparkSession, sf_dir: str, motion: bool = True, cut: float = pairing.CUT, classes: tuple[str, ...] = (), cameras: int = 2) -> MediaFrame:
    rule = DecomposeAssociation(detector(spark, sf_dir, cameras), refiner(spark, sf_dir, cameras), vision.track_column, _pair(motion, cut), _settle, pairing.to_association, classes)
    return one_shot_plan(spark, sf_dir, cameras).rewrite(rule)


def _flat(associations: DataFrame) -> DataFrame:
    a, t = F.col("attributes"), F.col("timeline")
    line = F.concat_ws(";", F.transform(t, lambda x: F.concat_ws(",", x["source_id"], x["start_ms"], x["end_ms"])))
    return associations.select("scene_id", "vehicle_id", a["class"].alias("class"), a["colour"].alias("colour"), a["subtype"].alias("subtype"), line.alias("timeline"), F.round("match_score", 6).alias("match_score"))


def xcam_oneshot(spark, sf_dir):
    return _flat(one_shot_plan(spark, sf_dir).to_df().select("scene_id", "A.*"))


def xcam_staged(spark, sf_dir):
    return _flat(staged_plan(spark, sf_dir).to_df()).drop("vehicle_id")


def xcam_detections(spark, sf_dir):
    d = staged_plan(spark, sf_dir).stage("detections").select("source_id", F.explode("_d").alias("d"))
    return d.select("source_id", "d.frame_no", "d.det_id", "d.x", "d.y", "d.w", "d.h", "d.conf")


def nms(spark, sf_dir):
    d = vision.suppress_column(staged_plan(spark, sf_dir).stage("detections").drop("v"), "_d").select("source_id", F.explode("_d").alias("d"))
    return d.select("source_id", "d.frame_no", "d.x", "d.y", "d.conf")


def tracks(spark, sf_dir) -> DataFrame:
    return staged_plan(spark, sf_dir).stage("tracks").select("scene_id", "source_id", "_t.*")


def xcam_tracks(spark, sf_dir):
    return tracks(spark, sf_dir).select("source_id", "start_ms", "end_ms", "n_det", "first_x", "first_y", "last_x", "last_y")


CHUNK_FRAMES = 25


def xcam_tracks_chunked(spark, sf_dir):
    """The same tracks from chunks of a feed: each is tracked alone, pieces that continue each other are linked, and links close into tracks."""
    refined = staged_plan(spark, sf_dir).stage("refined").select("source_id", F.explode("_d").alias("d"))
    chunks = refined.groupBy("source_id", F.expr(f"d.frame_no div {CHUNK_FRAMES}").alias("chunk")).agg(F.array_sort(F.collect_list("d")).alias("_d"))
    pieces = barrier(vision.track_column(chunks, "_d", "_t", vision.MotionTracker(min_length=1)).select("source_id", "chunk", F.explode("_t").alias("t")).select("source_id", "chunk", "t.*").drop("emb"))
    key = lambda chunk, track: F.concat_ws(":", F.lpad(F.col("source_id").cast("string"), 12, "0"), F.lpad(chunk.cast("string"), 9, "0"), F.lpad(F.col(track).cast("string"), 6, "0"))
    links = vision.stitch(pieces).select(key(F.col("chunk"), "l_track_id").alias("a"), key(F.col("chunk") + 1, "r_track_id").alias("b"))
    groups = matching.connected_groups(links)
    placed = pieces.withColumn("node", key(F.col("chunk"), "track_id")).join(groups, "node", "left").withColumn("group", F.coalesce("group", "node"))
    ends = lambda c, place: F.min_by(c, "first_frame") if place == "first" else F.max_by(c, "last_frame")
    whole = placed.groupBy("source_id", "group").agg(
        F.min("start_ms").alias("start_ms"), F.max("end_ms").alias("end_ms"), F.sum("n_det").cast("int").alias("n_det"),
        *[ends(f"{place}_{c}", place).alias(f"{place}_{c}") for place in ("first", "last") for c in ("x", "y")],
    )
    return whole.where("n_det >= 3").select("source_id", "start_ms", "end_ms", "n_det", "first_x", "first_y", "last_x", "last_y")


def udtf_track_boxes(spark, sf_dir):
    """Tracks from flat detections by a table function in SQL: partitioned by source, in order of frame."""
    from mediarel import sql

    sql.register(spark)
    d = vision.suppress_column(staged_plan(spark, sf_dir).stage("detections").drop("v"), "_d").select("source_id", F.explode("_d").alias("d")).select("source_id", "d.*")
    found = spark.sql("SELECT source_id, start_ms, end_ms, n_det FROM track_boxes(TABLE({d}) PARTITION BY source_id ORDER BY (frame_no, det_id))", d=d)
    return found


def _pair_columns(df: DataFrame) -> DataFrame:
    return df.select("scene_id", "left_source", "right_source", F.col("l_start_ms").alias("left_start_ms"), F.col("l_first_y").alias("left_y"), F.col("r_start_ms").alias("right_start_ms"), F.col("r_first_y").alias("right_y"), "score")


def xcam_pairs(spark, sf_dir):
    return _pair_columns(staged_plan(spark, sf_dir).stage("pairs"))


def xcam_matches(spark, sf_dir):
    return _pair_columns(staged_plan(spark, sf_dir).stage("matches"))


def pair_candidates(spark, sf_dir):
    found = pairing.candidates(tracks(spark, sf_dir))
    return found.select("scene_id", F.col("l_source_id").alias("left_source"), F.col("r_source_id").alias("right_source"), F.col("l_first_y").alias("left_y"), F.col("r_first_y").alias("right_y"))


def cosine_pairs(spark, sf_dir):
    found = pairing.scored(pairing.candidates(tracks(spark, sf_dir), motion=False), -1.0)
    return found.select("scene_id", F.col("l_first_y").alias("left_y"), F.col("r_first_y").alias("right_y"), "score")


def references(spark, sf_dir) -> DataFrame:
    """Vehicles that both cameras see, with their real attributes and times: for measures only."""
    v = vehicles(spark, sf_dir)
    side = lambda c: v.where(F.col("camera") == c).select("k", "scene_id", "cls", "colour", "subtype", F.col("source_id").alias(f"s{c}"), (F.col("first_frame") * 100).cast("bigint").alias(f"b{c}"), ((F.col("first_frame") + 25) * 100).cast("bigint").alias(f"e{c}"))
    return side(0).join(side(1).select("k", "s1", "b1", "e1"), "k")


def _assoc_matches(pred: DataFrame, ref: DataFrame) -> DataFrame:
    line = lambda i: F.col("timeline")[i]
    p = pred.select("scene_id", "vehicle_id", F.col("attributes")["class"].alias("pc"), F.col("attributes")["colour"].alias("pk"), F.col("attributes")["subtype"].alias("ps"), *[line(i)[f].alias(f"p{f[0]}{i}") for i in (0, 1) for f in ("start_ms", "end_ms")])
    pairs = p.join(ref, "scene_id")
    overlap = (tiou(F.col("ps0"), F.col("pe0"), F.col("b0"), F.col("e0")) + tiou(F.col("ps1"), F.col("pe1"), F.col("b1"), F.col("e1"))) / 2
    soft = measures.soft_agreement({"c": F.col("pc"), "k": F.col("pk"), "s": F.col("ps")}, {"c": F.col("cls"), "k": F.col("colour"), "s": F.col("subtype")})
    exact = ((F.col("pc") == F.col("cls")).cast("int") + (F.col("pk") == F.col("colour")).cast("int") + (F.col("ps") == F.col("subtype")).cast("int")) / 3
    scored = pairs.select("scene_id", "vehicle_id", "k", overlap.alias("time_iou"), exact.alias("exact"), F.round(measures.assoc_score(overlap, soft), 6).alias("score"))
    accepted = scored.where("score >= 0.7")
    return matching.greedy(accepted, ["scene_id"], "vehicle_id", "k", "score")


def m_assoc_score(spark, sf_dir):
    return _assoc_matches(one_shot_plan(spark, sf_dir).to_df().select("scene_id", "A.*"), references(spark, sf_dir)).select("scene_id", "k", "score", F.round("time_iou", 6).alias("time_iou"), F.round("exact", 6).alias("exact"))


def m_assoc_prf(spark, sf_dir):
    ref = references(spark, sf_dir)
    found = None
    for name, pred in (("oneshot", one_shot_plan(spark, sf_dir).to_df().select("scene_id", "A.*")), ("staged", staged_plan(spark, sf_dir).to_df())):
        won = _assoc_matches(pred, ref).agg(F.count("*").alias("tp"), F.round(F.avg("time_iou"), 6).alias("timeline_iou"), F.round(F.avg("exact"), 6).alias("attr_exact"))
        rows = won.crossJoin(measures.counted(pred, "n_pred")).crossJoin(measures.counted(ref, "n_ref")).withColumn("plan", F.lit(name))
        found = rows if found is None else found.unionByName(rows)
    told = measures.prf(found).withColumns({"fp": F.col("n_pred") - F.col("tp"), "fn": F.col("n_ref") - F.col("tp")})
    return told.select("plan", "n_pred", "tp", "fp", "fn", "precision", "recall", "f1", "timeline_iou", "attr_exact")


def _usable(spark, sf_dir) -> DataFrame:
    """(k, camera) of vehicles with a track of their lane and of half their time or more."""
    v = vehicles(spark, sf_dir).select("k", "camera", "source_id", (F.col("k") % 20 * 60).cast("double").alias("first_y"), (F.col("first_frame") * 100).cast("bigint").alias("b"), ((F.col("first_frame") + 25) * 100).cast("bigint").alias("e"))
    found = v.join(tracks(spark, sf_dir).select("source_id", "first_y", "start_ms", "end_ms"), ["source_id", "first_y"])
    return found.where(tiou(F.col("b"), F.col("e"), F.col("start_ms"), F.col("end_ms")) >= 0.5).select("k", "camera").distinct()


def m_entity_coverage(spark, sf_dir):
    usable = _usable(spark, sf_dir).groupBy("k").agg(F.count("*").alias("n")).where("n = 2").withColumn("hit", F.lit(1)).select("k", "hit")
    sums = references(spark, sf_dir).select("k").join(usable, "k", "left").agg(F.count("*").alias("n_ref"), F.count("hit").alias("n_covered"))
    return sums.select(F.lit("tracks").alias("stage"), "n_ref", "n_covered", F.round(F.col("n_covered") / F.col("n_ref"), 6).alias("coverage"))


def _right_pairs(pairs: DataFrame) -> DataFrame:
    return pairs.where("left_y = right_y").select((F.col("scene_id") * 20 + F.col("left_y") / 60).cast("bigint").alias("k")).distinct()


def m_pair_coverage(spark, sf_dir):
    plan = staged_plan(spark, sf_dir)
    ref = references(spark, sf_dir).select("k")
    found = None
    for stage in ("pairs", "matches"):
        hit = _right_pairs(_pair_columns(plan.stage(stage))).withColumn("hit", F.lit(1))
        rows = ref.join(hit, "k", "left").agg(F.count("*").alias("n_ref"), F.count("hit").alias("n_covered")).withColumn("stage", F.lit(stage))
        found = rows if found is None else found.unionByName(rows)
    return found.select("stage", "n_ref", "n_covered", F.round(F.col("n_covered") / F.col("n_ref"), 6).alias("coverage"))


def xcam_cut_sweep(spark, sf_dir):
    """Pairs kept and right pairs kept for each appearance cut, with and without the motion gate: one scoring pass."""
    seen = tracks(spark, sf_dir)
    found = None
    for motion in (True, False):
        rows = pairing.scored(pairing.candidates(seen, motion), -1.0).select("score", (F.col("l_first_y") == F.col("r_first_y")).cast("int").alias("right"))
        swept = rows.select("score", "right", F.explode(F.array(*[F.lit(c) for c in CUTS])).alias("cut")).where("score >= cut")
        part = swept.groupBy("cut").agg(F.count("*").alias("n_pairs"), F.sum("right").alias("n_right")).withColumn("motion", F.lit(motion))
        found = part if found is None else found.unionByName(part)
    return found.select("motion", "cut", "n_pairs", "n_right")


def xcam_multi(spark, sf_dir):
    """Three feeds a scene: matches of every source pair closed over tracks; one row an entity with its feeds in order."""
    m = staged_plan(spark, sf_dir, cameras=3).stage("matches")
    key = lambda s: F.concat_ws(":", F.lpad(F.col(f"{s}_source_id").cast("string"), 12, "0"), F.lpad(F.col(f"{s}_track_id").cast("string"), 6, "0"))
    groups = matching.connected_groups(m.select(key("l").alias("a"), key("r").alias("b")))
    feeds = F.array_sort(F.collect_list(F.split("node", ":")[0].cast("bigint")))
    entities = groups.groupBy("group").agg(F.count("*").alias("n_tracks"), F.concat_ws(",", feeds).alias("feeds"))
    return entities.groupBy("feeds", "n_tracks").agg(F.count("*").alias("n_entities"))


def embed_lookup(spark, sf_dir):
    return crops(spark, sf_dir).select("crop", F.round(F.element_at("emb", 1), 6).alias("e1"), F.round(F.aggregate("emb", F.lit(0.0), lambda t, x: t + x), 6).alias("total"))


def vehicles_sql(cameras: int) -> str:
    """CTEs of vehicles, tracks and scored pairs of a scene's cameras."""
    return f"""
n AS (SELECT count(*) AS n FROM embeddings), np AS (SELECT count(*) AS np FROM part),
v AS (
  SELECT vec_id AS k, camera, vec_id // 20 AS scene_id, (vec_id // 20) * {cameras} + camera AS source_id, (vec_id * 3) % 20 + camera * (vec_id % 5) AS ff,
         CASE WHEN vec_id % 2 = 1 THEN -1 ELSE 1 END * (8 + vec_id % 5) AS speed, p_type AS cls, split_part(p_name, ' ', 1) AS colour, p_brand AS subtype, CAST(60 * (vec_id % 20) AS DOUBLE) AS y
  FROM embeddings CROSS JOIN (SELECT unnest(range({cameras})) AS camera) CROSS JOIN np JOIN part ON p_partkey = vec_id % np
  WHERE NOT (camera = 0 AND vec_id % 11 = 0) AND NOT (camera = 1 AND vec_id % 7 = 0) AND NOT (camera = 2 AND vec_id % 13 = 0)),
f AS (SELECT v.*, ff + i AS frame_no, CAST(700 + speed * (ff + i) + 300 * camera AS DOUBLE) AS x FROM v CROSS JOIN (SELECT unnest(range(25)) AS i) WHERE (k * 3 + ff + i) % 10 <> 0),
t AS (
  SELECT k, camera, scene_id, source_id, cls, subtype, CASE WHEN camera = 1 AND k % 5 = 2 THEN 'unknown' ELSE colour END AS colour, y, speed, min(frame_no) * 100 AS start_ms, (max(frame_no) + 1) * 100 AS end_ms,
         count(*) AS n_det, arg_min(x, frame_no) AS first_x, arg_max(x, frame_no) AS last_x
  FROM f GROUP BY k, camera, scene_id, source_id, cls, subtype, colour, y, speed),
vec AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
crop AS MATERIALIZED (
  SELECT a.vec_id AS k, camera, list_transform(list_zip(a.e, b.e), lambda z: z[1] + z[2] * CASE WHEN a.vec_id % 9 = 0 AND camera = 1 THEN 3.0 ELSE 0.5 END) AS emb
  FROM vec a CROSS JOIN (SELECT unnest(range({cameras})) AS camera) CROSS JOIN n JOIN vec b ON b.vec_id = (a.vec_id * 13 + 7 * camera + 5) % n),
tv AS MATERIALIZED (SELECT t.*, emb FROM t JOIN crop USING (k, camera)),
allpairs AS (
  SELECT l.k AS lk, r.k AS rk, l.scene_id, l.source_id AS left_source, r.source_id AS right_source, l.start_ms AS left_start_ms, l.end_ms AS left_end_ms, l.y AS left_y, r.start_ms AS right_start_ms, r.end_ms AS right_end_ms, r.y AS right_y,
         l.cls AS cls, l.subtype AS subtype, CASE WHEN l.colour = 'unknown' THEN r.colour ELSE l.colour END AS colour,
         l.speed * r.speed > 0 AND greatest(abs(l.speed), abs(r.speed)) <= 1.25 * least(abs(l.speed), abs(r.speed)) + 1e-9 AS alike,
         round(list_cosine_similarity(l.emb, r.emb), 6) AS score, l.first_x AS lx, r.first_x AS rx
  FROM tv l JOIN tv r ON l.scene_id = r.scene_id AND l.source_id < r.source_id AND l.start_ms < r.end_ms AND r.start_ms < l.end_ms),
pairs AS (SELECT * FROM allpairs WHERE alike AND score >= 0.4)"""


VEHICLES_SQL = vehicles_sql(2)
# Greedy by score, then by the places of the tracks in their sources (first frame, x, y).
MATCHES_SQL = f"""
WITH RECURSIVE {VEHICLES_SQL},
ranked AS (SELECT *, row_number() OVER (PARTITION BY scene_id ORDER BY score DESC, left_start_ms, lx, left_y, right_start_ms, rx, right_y) AS p FROM pairs),
walk AS (
  SELECT scene_id, p, lk, rk, TRUE AS kept, [lk] AS ul, [rk] AS ur FROM ranked WHERE p = 1
  UNION ALL
  SELECT r.scene_id, r.p, r.lk, r.rk, NOT (list_contains(ul, r.lk) OR list_contains(ur, r.rk)),
         CASE WHEN list_contains(ul, r.lk) OR list_contains(ur, r.rk) THEN ul ELSE list_append(ul, r.lk) END,
         CASE WHEN list_contains(ul, r.lk) OR list_contains(ur, r.rk) THEN ur ELSE list_append(ur, r.rk) END
  FROM walk w JOIN ranked r ON r.scene_id = w.scene_id AND r.p = w.p + 1),
matches AS (SELECT r.* FROM ranked r JOIN walk w ON r.scene_id = w.scene_id AND r.p = w.p WHERE kept),
refs AS (SELECT a.k, a.scene_id, a.cls, a.colour, a.subtype, a.ff AS f0, b.ff AS f1, a.source_id AS s0, b.source_id AS s1 FROM v a JOIN v b ON a.k = b.k AND a.camera = 0 AND b.camera = 1),
oneshot AS (SELECT * FROM refs WHERE k % 5 = 0)"""

QUERIES = {
    f.__name__: f
    for f in (
        xcam_oneshot, xcam_staged, xcam_detections, nms, xcam_tracks, xcam_pairs, xcam_matches, pair_candidates, cosine_pairs, m_assoc_score, m_assoc_prf,
        m_entity_coverage, m_pair_coverage, xcam_cut_sweep, xcam_multi, embed_lookup, udtf_track_boxes, xcam_tracks_chunked,
    )
}
QUERIES["media_track"] = xcam_tracks
QUERIES["media_detect"] = xcam_detections

_DETECTIONS = f"""WITH {VEHICLES_SQL},
b AS (SELECT source_id, frame_no, x + o AS x, y, CASE WHEN o = 0 THEN 0.9 ELSE 0.6 END AS conf FROM (SELECT *, unnest(CASE WHEN (k + frame_no) % 6 = 0 THEN [0, 4] ELSE [0] END) AS o FROM f))
SELECT source_id, frame_no, row_number() OVER (PARTITION BY source_id ORDER BY frame_no, x, y) AS det_id, x, y, CAST(50 AS DOUBLE) AS w, CAST(40 AS DOUBLE) AS h, CAST(conf AS DOUBLE) AS conf FROM b"""
_TRACKS = f"WITH {VEHICLES_SQL} SELECT source_id, start_ms, end_ms, n_det, first_x, y AS first_y, last_x, y AS last_y FROM t"
_TIOU = "greatest(least({e1}, {e2}) - greatest({s1}, {s2}), 0) / (({e1}) - ({s1}) + ({e2}) - ({s2}) - greatest(least({e1}, {e2}) - greatest({s1}, {s2}), 0))"
_SOFT = "(CASE WHEN {a} = 'unknown' OR {b} = 'unknown' THEN 0.5 WHEN {a} = {b} THEN 1.0 ELSE 0.0 END)"
_ATTRIBUTES = [(f"o.{c}", f"r.{c}") for c in ("cls", "colour", "subtype")]
_ASSOC_SQL = f"""{MATCHES_SQL},
reported AS (
  SELECT 'oneshot' AS plan, scene_id, k AS o, cls, colour, subtype, f0 * 100 AS b0, f0 * 100 + 1800 AS e0, f1 * 100 AS b1, f1 * 100 + 1800 AS e1 FROM oneshot
  UNION ALL SELECT 'staged', scene_id, p, cls, colour, subtype, left_start_ms, left_end_ms, right_start_ms, right_end_ms FROM matches),
compared AS (
  SELECT plan, o.scene_id, o, r.k, (({_TIOU.format(s1="o.b0", e1="o.e0", s2="r.f0*100", e2="r.f0*100+2500")}) + ({_TIOU.format(s1="o.b1", e1="o.e1", s2="r.f1*100", e2="r.f1*100+2500")})) / 2 AS time_iou,
         ({" + ".join(f"CAST({a} = {b} AS INT)" for a, b in _ATTRIBUTES)}) / 3 AS exact, ({" + ".join(_SOFT.format(a=a, b=b) for a, b in _ATTRIBUTES)}) / 3 AS soft
  FROM reported o JOIN refs r ON o.scene_id = r.scene_id),
placed AS (
  SELECT *, round(0.7 * time_iou + 0.3 * soft, 6) AS score, row_number() OVER (PARTITION BY plan, scene_id ORDER BY round(0.7 * time_iou + 0.3 * soft, 6) DESC, o, k) AS q
  FROM compared WHERE round(0.7 * time_iou + 0.3 * soft, 6) >= 0.7),
settle AS (
  SELECT plan, scene_id, q, o, k, TRUE AS kept, [o] AS uo, [k] AS uk FROM placed WHERE q = 1
  UNION ALL
  SELECT c.plan, c.scene_id, c.q, c.o, c.k, NOT (list_contains(uo, c.o) OR list_contains(uk, c.k)),
         CASE WHEN list_contains(uo, c.o) OR list_contains(uk, c.k) THEN uo ELSE list_append(uo, c.o) END,
         CASE WHEN list_contains(uo, c.o) OR list_contains(uk, c.k) THEN uk ELSE list_append(uk, c.k) END
  FROM settle w JOIN placed c ON c.plan = w.plan AND c.scene_id = w.scene_id AND c.q = w.q + 1),
accepted AS (SELECT p.* FROM placed p JOIN settle s ON p.plan = s.plan AND p.scene_id = s.scene_id AND p.q = s.q WHERE kept)"""

ORACLE_SQL = {
    "xcam_oneshot": f"{MATCHES_SQL} SELECT scene_id, scene_id || ':' || k AS vehicle_id, cls AS class, colour, subtype, s0 || ',' || f0 * 100 || ',' || (f0 * 100 + 1800) || ';' || s1 || ',' || f1 * 100 || ',' || (f1 * 100 + 1800) AS timeline, CAST(1 AS DOUBLE) AS match_score FROM oneshot",
    "xcam_staged": f"{MATCHES_SQL} SELECT scene_id, cls AS class, colour, subtype, left_source || ',' || left_start_ms || ',' || left_end_ms || ';' || right_source || ',' || right_start_ms || ',' || right_end_ms AS timeline, score AS match_score FROM matches",
    "xcam_detections": _DETECTIONS,
    "media_detect": _DETECTIONS,
    "nms": f"WITH {VEHICLES_SQL} SELECT source_id, frame_no, x, y, CAST(0.9 AS DOUBLE) AS conf FROM f",
    "udtf_track_boxes": f"WITH {VEHICLES_SQL} SELECT source_id, start_ms, end_ms, n_det FROM t WHERE n_det >= 3",
    "xcam_tracks_chunked": _TRACKS,
    "xcam_tracks": _TRACKS,
    "media_track": _TRACKS,
    "xcam_pairs": f"WITH {VEHICLES_SQL} SELECT scene_id, left_source, right_source, left_start_ms, left_y, right_start_ms, right_y, score FROM pairs",
    "xcam_matches": f"{MATCHES_SQL} SELECT scene_id, left_source, right_source, left_start_ms, left_y, right_start_ms, right_y, score FROM matches",
    "pair_candidates": f"WITH {VEHICLES_SQL} SELECT scene_id, left_source, right_source, left_y, right_y FROM allpairs WHERE alike",
    "cosine_pairs": f"WITH {VEHICLES_SQL} SELECT scene_id, left_y, right_y, score FROM allpairs",
    "embed_lookup": f"WITH {VEHICLES_SQL} SELECT k * 2 + camera AS crop, round(emb[1], 6) AS e1, round(list_sum(emb), 6) AS total FROM crop",
    "xcam_cut_sweep": f"""WITH {VEHICLES_SQL}, c AS (SELECT CAST(unnest([0.2, 0.3, 0.4, 0.5, 0.6]) AS DOUBLE) AS cut), m AS (SELECT unnest([TRUE, FALSE]) AS motion)
SELECT motion, cut, count(*) AS n_pairs, CAST(sum(CAST(left_y = right_y AS INT)) AS BIGINT) AS n_right FROM allpairs CROSS JOIN c CROSS JOIN m WHERE score >= cut AND (alike OR NOT motion) GROUP BY motion, cut""",
    "xcam_multi": f"""WITH RECURSIVE {vehicles_sql(3)},
ranked AS (SELECT *, row_number() OVER (PARTITION BY scene_id, left_source, right_source ORDER BY score DESC, left_start_ms, lx, left_y, right_start_ms, rx, right_y) AS p FROM pairs),
walk AS (
  SELECT left_source, right_source, p, lk, rk, TRUE AS kept, [lk] AS ul, [rk] AS ur FROM ranked WHERE p = 1
  UNION ALL
  SELECT r.left_source, r.right_source, r.p, r.lk, r.rk, NOT (list_contains(ul, r.lk) OR list_contains(ur, r.rk)),
         CASE WHEN list_contains(ul, r.lk) OR list_contains(ur, r.rk) THEN ul ELSE list_append(ul, r.lk) END,
         CASE WHEN list_contains(ul, r.lk) OR list_contains(ur, r.rk) THEN ur ELSE list_append(ur, r.rk) END
  FROM walk w JOIN ranked r ON r.left_source = w.left_source AND r.right_source = w.right_source AND r.p = w.p + 1),
edge AS (SELECT left_source * 100000 + lk AS a, right_source * 100000 + rk AS b FROM walk WHERE kept),
both_ways AS (SELECT a, b FROM edge UNION SELECT b, a FROM edge),
reach AS (SELECT a AS node, a AS root FROM both_ways UNION SELECT g.b, reach.root FROM reach JOIN both_ways g ON g.a = reach.node),
entity AS (SELECT root, count(*) AS n_tracks, string_agg(node // 100000, ',' ORDER BY node // 100000) AS feeds FROM (SELECT node, min(root) AS root FROM reach GROUP BY node) GROUP BY root)
SELECT feeds, n_tracks, count(*) AS n_entities FROM entity GROUP BY feeds, n_tracks""",
    "m_assoc_score": f"{_ASSOC_SQL} SELECT scene_id, k, CAST(score AS DOUBLE) AS score, round(time_iou, 6) AS time_iou, round(exact, 6) AS exact FROM accepted WHERE plan = 'oneshot'",
    "m_assoc_prf": f"""{_ASSOC_SQL},
a AS (SELECT plan, count(*) AS tp, round(avg(time_iou), 6) AS timeline_iou, round(avg(exact), 6) AS attr_exact FROM accepted GROUP BY plan)
SELECT a.plan, n_pred, tp, n_pred - tp AS fp, n_ref - tp AS fn, round(tp / n_pred, 6) AS precision, round(tp / n_ref, 6) AS recall, round(2 * tp / (n_pred + n_ref), 6) AS f1, timeline_iou, attr_exact
FROM a JOIN (SELECT plan, count(*) AS n_pred FROM reported GROUP BY plan) p ON a.plan = p.plan CROSS JOIN (SELECT count(*) AS n_ref FROM refs)""",
    "m_entity_coverage": f"""{MATCHES_SQL},
u AS (SELECT k FROM (SELECT v.k FROM v JOIN t ON v.k = t.k AND v.camera = t.camera WHERE {_TIOU.format(s1="ff*100", e1="ff*100+2500", s2="start_ms", e2="end_ms")} >= 0.5) GROUP BY k HAVING count(*) = 2)
SELECT 'tracks' AS stage, count(*) AS n_ref, count(u.k) AS n_covered, round(count(u.k) / count(*), 6) AS coverage FROM refs LEFT JOIN u ON refs.k = u.k""",
    "m_pair_coverage": f"""{MATCHES_SQL},
h AS (SELECT 'pairs' AS stage, lk AS k FROM pairs WHERE lk = rk UNION ALL SELECT 'matches', lk FROM matches WHERE lk = rk),
st AS (SELECT unnest(['pairs', 'matches']) AS stage)
SELECT st.stage, count(*) AS n_ref, count(h.k) AS n_covered, round(count(h.k) / count(*), 6) AS coverage FROM refs CROSS JOIN st LEFT JOIN h ON h.k = refs.k AND h.stage = st.stage GROUP BY st.stage""",
}
