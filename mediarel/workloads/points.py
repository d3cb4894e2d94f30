"""Point events in event streams: direct, narration and narrow-then-watch plans with their measures.

A user's events are a source on a compressed clock. Annotators are simulated: they see footage or
utterances, never references; how often they miss or invent is a fixture parameter.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from mediarel import measures
from mediarel.functions.semantic import SemanticFn, reading, watching
from mediarel.operators import intervals, reconcile
from mediarel.plans.frame import MediaFrame
from mediarel.plans.rules import PushdownWindows, SubstituteModality
from mediarel.schema import CANDIDATE, EVENT, media_ref
from mediarel.sources.stored import barrier

DURATION = 4_320_000
LONG_CONTEXT = 600_000
BEFORE, AFTER, MERGE = 20_000, 10_000, 2_000
TOLERANCES = (5_000, 10_000, 30_000, 60_000)


def footage(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    ts = F.expr("timestampdiff(MICROSECOND, timestamp_ntz'2024-01-01 00:00:00', ts) div 600000")
    return events.select(F.col("user_id").alias("source_id"), "event_id", ts.alias("ts_ms"), F.col("event_type").alias("kind"), "value")


def sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    users = spark.read.parquet(f"{sf_dir}/events.parquet").select(F.col("user_id").alias("source_id")).distinct()
    with_time = users.withColumn("duration_ms", F.lit(DURATION).cast("bigint"))
    return with_time.withColumn("v", media_ref(F.col("source_id"), F.col("duration_ms")))


def reference(spark: SparkSession, sf_dir: str) -> DataFrame:
    return footage(spark, sf_dir).where("kind = 'purchase' AND value >= 120").select("source_id", "event_id", "ts_ms")


def utterances(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Displaced narration of goals and near goals: the stored transcript."""
    told = footage(spark, sf_dir).where("kind IN ('purchase', 'error') AND value >= 120")
    delay = F.expr("CASE WHEN event_id % 29 = 0 THEN 45000 ELSE ((event_id * 37) % 13 - 2) * 1000 END")
    text = F.expr("CASE WHEN kind = 'purchase' OR event_id % 8 = 5 THEN 'goal' ELSE 'close call' END")
    return told.select("source_id", "event_id", F.greatest(F.col("ts_ms") + delay, F.lit(0)).cast("bigint").alias("start_ms"), text.alias("text"))


def _attach(df: DataFrame, found: DataFrame, keys: list[str], into: str, kind: str) -> DataFrame:
    """Events (keys, start_ms, end_ms, conf, evidence) as a collection beside every row; rows without any get an empty one."""
    lists = found.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("start_ms", "end_ms", "conf", "evidence"))).alias(into))
    return df.join(lists, keys, "left").withColumn(into, F.coalesce(F.col(into), F.array().cast(kind)))


def task(spark: SparkSession, sf_dir: str) -> SemanticFn:
    """Locate goals, over footage (``v``) and over the transcript (``t``)."""
    seen = footage(spark, sf_dir)

    def watch(df: DataFrame, on: str, into: str) -> DataFrame:
        clip = F.col(on)
        spans = df.select("source_id", clip["clip_start_ms"].alias("s"), clip["clip_end_ms"].alias("e"))
        # What is watched meets its footage on time buckets.
        rows = intervals.point_join(seen.where("kind IN ('purchase', 'error') AND value >= 120"), spans, ["source_id"], LONG_CONTEXT, span=("s", "e"))
        long = F.expr(f"e - s > {LONG_CONTEXT}")
        goal = F.col("kind") == "purchase"
        told = F.when(goal, ~(long & F.expr("event_id % 10 = 3"))).otherwise(F.when(long, F.expr("event_id % 6 = 1")).otherwise(F.expr("event_id % 24 = 1")))
        at = F.col("ts_ms") - F.col("s") + F.expr("((event_id * 7) % 5 - 2) * 100")
        found = rows.where(told).select("source_id", "s", "e", at.alias("start_ms"), at.alias("end_ms"), F.when(goal, 0.9).otherwise(0.6).alias("conf"), F.lit("seen").alias("evidence"))
        keyed = df.withColumns({"s": clip["clip_start_ms"], "e": clip["clip_end_ms"]})
        return _attach(keyed, found, ["source_id", "s", "e"], into, f"array<{EVENT}>").drop("s", "e")

    def read(df: DataFrame, on: str, into: str) -> DataFrame:
        goals = F.filter(F.col(on), lambda u: u["text"] == "goal")
        return df.withColumn(into, F.transform(goals, lambda u: F.struct(u["start_ms"].alias("start_ms"), u["start_ms"].alias("end_ms"), F.lit(0.7).alias("conf"), u["text"].alias("evidence"))))

    output = f"array<{EVENT}>"
    narrated = SemanticFn("goals in narration", "Return the time of every goal.", "t", output, read, meter=reading)
    return SemanticFn("goals in footage", "Return the time of every goal.", "v", output, watch, siblings={"t": narrated}, meter=watching)


def candidates_fn() -> SemanticFn:
    """Recall first: every utterance may stand near a goal."""

    def run(df: DataFrame, on: str, into: str) -> DataFrame:
        return df.withColumn(into, F.transform(F.col(on), lambda u: F.struct(u["start_ms"].alias("start_ms"), u["start_ms"].alias("end_ms"), F.lit(1.0).alias("score"))))

    return SemanticFn("goal candidates", "Return every moment that may be near a goal.", "t", f"array<{CANDIDATE}>", run, meter=reading)


def relation(spark: SparkSession, sf_dir: str) -> MediaFrame:
    """(source_id, duration_ms, v, t): the transcript is stored and only read."""
    told = utterances(spark, sf_dir).groupBy("source_id").agg(F.array_sort(F.collect_list(F.struct("start_ms", "event_id", "text"))).alias("t"))
    both = sources(spark, sf_dir).join(told, "source_id", "left")
    kind = "array<struct<start_ms:bigint,event_id:bigint,text:string>>"
    return MediaFrame.of(both.withColumn("t", F.coalesce(F.col("t"), F.array().cast(kind))), "streams")


def direct(spark: SparkSession, sf_dir: str) -> MediaFrame:
    return relation(spark, sf_dir).derive({"events": task(spark, sf_dir)}, on="v").unnest("events")


def narration(spark: SparkSession, sf_dir: str) -> MediaFrame:
    return direct(spark, sf_dir).rewrite(SubstituteModality("v", "t"))


def narrow(spark: SparkSession, sf_dir: str, before_ms: int = BEFORE, after_ms: int = AFTER) -> MediaFrame:
    return direct(spark, sf_dir).rewrite(PushdownWindows(candidates_fn(), "t", before_ms, after_ms, reconcile.points(MERGE)))


def told(found: DataFrame) -> DataFrame:
    """Predictions of a plan's result."""
    return found.select("source_id", F.col("events.start_ms").alias("ts_ms"))


def _points(plan: MediaFrame) -> DataFrame:
    return told(plan.to_df())


PLANS = {"direct": direct, "narration": narration, "narrow": narrow}


def point_direct(spark, sf_dir):
    return _points(direct(spark, sf_dir))


def point_narration(spark, sf_dir):
    return _points(narration(spark, sf_dir))


def point_narrow(spark, sf_dir):
    return _points(narrow(spark, sf_dir))


def point_candidates(spark, sf_dir):
    low = F.greatest(F.col("start_ms") - BEFORE, F.lit(0).cast("bigint"))
    high = F.least(F.col("start_ms") + AFTER, F.lit(DURATION).cast("bigint"))
    return utterances(spark, sf_dir).select("source_id", "event_id", low.alias("start_ms"), high.alias("end_ms")).where("start_ms < end_ms")


def point_windows(spark, sf_dir):
    return narrow(spark, sf_dir).stage("windows").select("source_id", "window_no", "start_ms", "end_ms")


def narrow_keeps_all_sources(spark, sf_dir):
    plan = narrow(spark, sf_dir)
    folded = MediaFrame(plan.node.child).to_df()
    return folded.select("source_id", F.size("events").cast("bigint").alias("n_events"))


def point_narrow_meta(spark, sf_dir):
    """Narrowing by another aligned representation: source minutes with at least two purchases or errors."""
    plan = direct(spark, sf_dir)
    busy = footage(spark, sf_dir).where("kind IN ('purchase', 'error')").groupBy("source_id", F.expr("ts_ms div 60000").alias("minute")).agg(F.count("*").alias("n")).where("n >= 2")
    spans = busy.groupBy("source_id").agg(F.array_sort(F.collect_list(F.struct((F.col("minute") * 60000).alias("start_ms"), (F.col("minute") * 60000 + 60000).alias("end_ms"), F.col("n").cast("double").alias("score")))).alias("_busy"))

    def run(df: DataFrame, on: str, into: str) -> DataFrame:
        return df.join(spans, "source_id", "left").withColumn(into, F.coalesce("_busy", F.array().cast(f"array<{CANDIDATE}>"))).drop("_busy")

    cand = SemanticFn("busy minutes", "Minutes with much going on.", "counts", f"array<{CANDIDATE}>", run)
    return _points(plan.rewrite(PushdownWindows(cand, "counts", 0, 0, reconcile.points(MERGE))))


def reconcile_points(spark, sf_dir):
    """Duplicate predictions of overlapping, uncoalesced windows reconciled to one set a source."""
    cuts = point_candidates(spark, sf_dir).select("source_id", "start_ms", "end_ms").distinct()
    inside = intervals.point_join(reference(spark, sf_dir), cuts, ["source_id"], 60_000)
    shaped = inside.select("source_id", F.col("ts_ms").alias("start_ms"), F.col("ts_ms").alias("end_ms"), F.lit(0.9).alias("conf"), F.lit("seen").alias("evidence"))
    return reconcile.chained_points(shaped, ["source_id"], MERGE).select("source_id", F.col("start_ms").alias("ts_ms"))


def _predictions(spark, sf_dir, plans) -> DataFrame:
    """Predictions of several plans, evaluated once: models are paid by the call."""
    found = None
    for name, plan in plans:
        rows = plan(spark, sf_dir).withColumn("plan", F.lit(name))
        found = rows if found is None else found.unionByName(rows)
    return barrier(found)


def m_point_curve(spark, sf_dir):
    preds = _predictions(spark, sf_dir, (("direct", point_direct), ("narration", point_narration), ("narrow", point_narrow)))
    return measures.point_curve(preds, reference(spark, sf_dir), TOLERANCES).withColumn("threshold", F.col("threshold").cast("bigint"))


def m_time_error(spark, sf_dir):
    ref = reference(spark, sf_dir)
    found = None
    for name, plan in (("narration", point_narration), ("narrow", point_narrow)):
        rows = measures.match_points(plan(spark, sf_dir), ref, 30_000).agg(
            F.count("*").alias("n_matched"), F.round(F.avg("error_ms"), 6).alias("mean_ms"), F.round(F.percentile("error_ms", F.lit(0.5)), 6).alias("median_ms")
        )
        rows = rows.withColumn("plan", F.lit(name))
        found = rows if found is None else found.unionByName(rows)
    return found.select("plan", "n_matched", "mean_ms", "median_ms")


def m_candidate_recall_point(spark, sf_dir):
    refs = reference(spark, sf_dir).select("source_id", F.col("ts_ms").alias("start_ms"), F.col("ts_ms").alias("end_ms"))
    return measures.candidate_recall(refs, point_windows(spark, sf_dir), ["source_id"])


def m_selectivity(spark, sf_dir):
    return measures.selectivity(point_windows(spark, sf_dir), sources(spark, sf_dir))


def m_selectivity_by_source(spark, sf_dir):
    return measures.selectivity_by_source(point_windows(spark, sf_dir), sources(spark, sf_dir))


PADS = (5_000, 10_000, 20_000, 40_000, 80_000)


def pad_sweep(spark, sf_dir):
    """Recall and selectivity for each padding before a candidate: one pass with the padding as part of the key."""
    pads = F.explode(F.array(*[F.lit(p).cast("bigint") for p in PADS])).alias("pad_ms")
    padded = utterances(spark, sf_dir).select("source_id", "start_ms", pads)
    low, high = F.greatest(F.col("start_ms") - F.col("pad_ms"), F.lit(0).cast("bigint")), F.least(F.col("start_ms") + AFTER, F.lit(DURATION).cast("bigint"))
    windows = intervals.coalesce(padded.select("source_id", "pad_ms", low.alias("start_ms"), high.alias("end_ms")).where("start_ms < end_ms"), ["pad_ms", "source_id"])
    refs = reference(spark, sf_dir)
    covered = intervals.point_join(refs, windows, ["source_id"], 60_000).groupBy("pad_ms").agg(F.countDistinct("event_id").alias("n_covered"))
    kept = windows.groupBy("pad_ms").agg(F.sum(F.col("end_ms") - F.col("start_ms")).cast("bigint").alias("window_ms"))
    return kept.join(covered, "pad_ms", "left").select("pad_ms", "window_ms", F.coalesce("n_covered", F.lit(0)).alias("n_covered"))


def displacement(spark, sf_dir):
    """As-of: how far the latest utterance lies before each goal. One shuffle and no cross pairs: union, order, carry on."""
    goals = reference(spark, sf_dir).select("source_id", F.col("ts_ms").alias("at"), F.col("event_id"), F.lit(None).cast("bigint").alias("said"))
    said = utterances(spark, sf_dir).select("source_id", F.col("start_ms").alias("at"), F.lit(None).cast("bigint").alias("event_id"), F.col("start_ms").alias("said"))
    order = Window.partitionBy("source_id").orderBy("at", F.col("said").isNull()).rowsBetween(Window.unboundedPreceding, 0)
    latest = goals.unionByName(said).withColumn("last_said", F.last("said", ignorenulls=True).over(order))
    return latest.where("event_id IS NOT NULL").select("source_id", "event_id", (F.col("at") - F.col("last_said")).alias("lag_ms"))


FOOTAGE_SQL = """
footage AS (SELECT user_id AS source_id, event_id, date_diff('microsecond', TIMESTAMP '2024-01-01', ts) // 600000 AS ts_ms, event_type AS kind, value FROM events),
sources AS (SELECT DISTINCT user_id AS source_id, CAST(4320000 AS BIGINT) AS duration_ms FROM events),
ref AS (SELECT source_id, event_id, ts_ms FROM footage WHERE kind = 'purchase' AND value >= 120),
utter AS (
  SELECT source_id, event_id, greatest(ts_ms + CASE WHEN event_id % 29 = 0 THEN 45000 ELSE ((event_id * 37) % 13 - 2) * 1000 END, 0) AS start_ms,
         CASE WHEN kind = 'purchase' OR event_id % 8 = 5 THEN 'goal' ELSE 'close call' END AS text
  FROM footage WHERE kind IN ('purchase', 'error') AND value >= 120),
cand AS (
  SELECT * FROM (SELECT source_id, event_id, greatest(start_ms - 20000, 0) AS start_ms, least(start_ms + 10000, 4320000) AS end_ms FROM utter) WHERE start_ms < end_ms)"""


def islands_sql(table: str, keys: str, into: str) -> str:
    """CTEs that coalesce half-open intervals of ``table`` by ``keys`` into ``into``."""
    return f"""
{into}_m AS (SELECT {keys}, start_ms, end_ms, max(end_ms) OVER (PARTITION BY {keys} ORDER BY start_ms, end_ms ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS reach FROM {table}),
{into}_g AS (SELECT *, sum(CASE WHEN reach IS NULL OR start_ms >= reach THEN 1 ELSE 0 END) OVER (PARTITION BY {keys} ORDER BY start_ms, end_ms ROWS UNBOUNDED PRECEDING) AS g FROM {into}_m),
{into} AS (SELECT {keys}, CAST(g - 1 AS BIGINT) AS window_no, min(start_ms) AS start_ms, max(end_ms) AS end_ms FROM {into}_g GROUP BY {keys}, g)"""


def seen_sql(spans: str, into: str) -> str:
    """What the simulated annotator returns on spans (source_id, s, e), in source time."""
    return f"""
{into} AS (
  SELECT f.source_id, f.ts_ms + ((event_id * 7) % 5 - 2) * 100 AS ts_ms, CASE WHEN kind = 'purchase' THEN 0.9 ELSE 0.6 END AS conf
  FROM footage f JOIN {spans} w ON f.source_id = w.source_id AND f.ts_ms >= w.s AND f.ts_ms < w.e
  WHERE value >= 120 AND ((kind = 'purchase' AND NOT (e - s > 600000 AND event_id % 10 = 3))
    OR (kind = 'error' AND ((e - s > 600000 AND event_id % 6 = 1) OR (e - s <= 600000 AND event_id % 24 = 1)))))"""


def chained_sql(table: str, into: str) -> str:
    return f"""
{into}_l AS (SELECT *, CASE WHEN ts_ms - lag(ts_ms) OVER (PARTITION BY source_id ORDER BY ts_ms, conf DESC) <= 2000 THEN 0 ELSE 1 END AS o FROM {table}),
{into}_g AS (SELECT *, sum(o) OVER (PARTITION BY source_id ORDER BY ts_ms, conf DESC ROWS UNBOUNDED PRECEDING) AS g FROM {into}_l),
{into} AS (SELECT source_id, ts_ms FROM (SELECT *, row_number() OVER (PARTITION BY source_id, g ORDER BY conf DESC, ts_ms) AS k FROM {into}_g) WHERE k = 1)"""


PLANS_SQL = f"""
{FOOTAGE_SQL},
{islands_sql('cand', 'source_id', 'windows')},
whole AS (SELECT source_id, CAST(0 AS BIGINT) AS s, duration_ms AS e FROM sources),
cut AS (SELECT source_id, start_ms AS s, end_ms AS e FROM windows),
{seen_sql('whole', 'direct')},
{seen_sql('cut', 'watched')},
{chained_sql('watched', 'narrow')},
narration AS (SELECT source_id, start_ms AS ts_ms FROM utter WHERE text = 'goal')"""

MATCH_SQL = f"""
WITH RECURSIVE {PLANS_SQL},
pred AS (
  SELECT 'direct' AS plan, source_id, ts_ms FROM direct UNION ALL SELECT 'narration', source_id, ts_ms FROM narration UNION ALL SELECT 'narrow', source_id, ts_ms FROM narrow),
tol AS (SELECT unnest([5000, 10000, 30000, 60000]) AS threshold),
pairs AS (
  SELECT plan, threshold, p.source_id, p.ts_ms AS a, r.ts_ms AS b, abs(p.ts_ms - r.ts_ms) AS err,
         row_number() OVER (PARTITION BY plan, threshold, p.source_id ORDER BY abs(p.ts_ms - r.ts_ms), p.ts_ms, r.ts_ms) AS k
  FROM pred p JOIN ref r ON p.source_id = r.source_id JOIN tol ON abs(p.ts_ms - r.ts_ms) <= threshold),
walk AS (
  SELECT plan, threshold, source_id, k, a, b, err, TRUE AS kept, [a] AS ua, [b] AS ub FROM pairs WHERE k = 1
  UNION ALL
  SELECT p.plan, p.threshold, p.source_id, p.k, p.a, p.b, p.err, NOT (list_contains(ua, p.a) OR list_contains(ub, p.b)),
         CASE WHEN list_contains(ua, p.a) OR list_contains(ub, p.b) THEN ua ELSE list_append(ua, p.a) END,
         CASE WHEN list_contains(ua, p.a) OR list_contains(ub, p.b) THEN ub ELSE list_append(ub, p.b) END
  FROM walk w JOIN pairs p ON p.plan = w.plan AND p.threshold = w.threshold AND p.source_id = w.source_id AND p.k = w.k + 1),
won AS (SELECT plan, threshold, source_id, err FROM walk WHERE kept)"""

QUERIES = {
    f.__name__: f
    for f in (
        point_direct, point_narration, point_candidates, point_windows, point_narrow, point_narrow_meta, narrow_keeps_all_sources, reconcile_points,
        m_point_curve, m_time_error, m_candidate_recall_point, m_selectivity, m_selectivity_by_source, pad_sweep,
    )
}
QUERIES["join_asof"] = displacement

ORACLE_SQL = {
    "point_direct": f"WITH {PLANS_SQL} SELECT source_id, ts_ms FROM direct",
    "point_narration": f"WITH {PLANS_SQL} SELECT source_id, ts_ms FROM narration",
    "point_candidates": f"WITH {FOOTAGE_SQL} SELECT source_id, event_id, start_ms, end_ms FROM cand",
    "point_windows": f"WITH {PLANS_SQL} SELECT source_id, window_no, start_ms, end_ms FROM windows",
    "point_narrow": f"WITH {PLANS_SQL} SELECT source_id, ts_ms FROM narrow",
    "narrow_keeps_all_sources": f"WITH {PLANS_SQL} SELECT s.source_id, CAST(count(n.ts_ms) AS BIGINT) AS n_events FROM sources s LEFT JOIN narrow n ON s.source_id = n.source_id GROUP BY s.source_id",
    "point_narrow_meta": f"""WITH {FOOTAGE_SQL},
busy AS (SELECT source_id, ts_ms // 60000 * 60000 AS start_ms, least(ts_ms // 60000 * 60000 + 60000, 4320000) AS end_ms FROM footage WHERE kind IN ('purchase', 'error') GROUP BY source_id, ts_ms // 60000 HAVING count(*) >= 2),
cut AS (SELECT source_id, start_ms AS s, end_ms AS e FROM busy),
{seen_sql('cut', 'watched')}, {chained_sql('watched', 'narrow')} SELECT source_id, ts_ms FROM narrow""",
    "reconcile_points": f"""WITH {FOOTAGE_SQL},
seen AS (SELECT r.source_id, r.ts_ms, 0.9 AS conf FROM ref r JOIN (SELECT DISTINCT source_id, start_ms, end_ms FROM cand) c ON r.source_id = c.source_id AND r.ts_ms >= c.start_ms AND r.ts_ms < c.end_ms),
{chained_sql('seen', 'kept')} SELECT source_id, ts_ms FROM kept""",
    "m_point_curve": f"""{MATCH_SQL}
SELECT np.plan, CAST(t.threshold AS BIGINT) AS threshold, CAST(coalesce(w.tp, 0) AS BIGINT) AS tp, np.n_pred, nr.n_ref, round(coalesce(w.tp, 0) / np.n_pred, 6) AS precision, round(coalesce(w.tp, 0) / nr.n_ref, 6) AS recall, round(2 * coalesce(w.tp, 0) / (np.n_pred + nr.n_ref), 6) AS f1
FROM (SELECT plan, count(*) AS n_pred FROM pred GROUP BY plan) np CROSS JOIN tol t CROSS JOIN (SELECT count(*) AS n_ref FROM ref) nr
LEFT JOIN (SELECT plan, threshold, count(*) AS tp FROM won GROUP BY plan, threshold) w ON w.plan = np.plan AND w.threshold = t.threshold""",
    "m_time_error": f"{MATCH_SQL} SELECT plan, count(*) AS n_matched, round(avg(err), 6) AS mean_ms, round(CAST(median(err) AS DOUBLE), 6) AS median_ms FROM won WHERE threshold = 30000 AND plan <> 'direct' GROUP BY plan",
    "m_candidate_recall_point": f"""WITH {PLANS_SQL},
c AS (SELECT r.event_id, max(CASE WHEN w.source_id IS NULL THEN 0 ELSE 1 END) AS hit FROM ref r LEFT JOIN windows w ON r.source_id = w.source_id AND r.ts_ms >= w.start_ms AND r.ts_ms < w.end_ms GROUP BY r.event_id)
SELECT count(*) AS n_ref, CAST(sum(hit) AS BIGINT) AS n_covered, round(sum(hit) / count(*), 6) AS recall FROM c""",
    "m_selectivity": f"WITH {PLANS_SQL} SELECT CAST(w AS BIGINT) AS window_ms, CAST(d AS BIGINT) AS source_ms, round(w / d, 6) AS selectivity FROM (SELECT sum(end_ms - start_ms) AS w FROM windows) CROSS JOIN (SELECT sum(duration_ms) AS d FROM sources)",
    "m_selectivity_by_source": f"""WITH {PLANS_SQL} SELECT s.source_id, CAST(coalesce(sum(end_ms - start_ms), 0) AS BIGINT) AS window_ms, round(coalesce(sum(end_ms - start_ms), 0) / max(duration_ms), 6) AS selectivity
FROM sources s LEFT JOIN windows w ON s.source_id = w.source_id GROUP BY s.source_id""",
    "pad_sweep": f"""WITH {FOOTAGE_SQL},
pads AS (SELECT unnest([5000, 10000, 20000, 40000, 80000]) AS pad_ms),
padded AS (SELECT * FROM (SELECT pad_ms, source_id, greatest(start_ms - pad_ms, 0) AS start_ms, least(start_ms + 10000, 4320000) AS end_ms FROM utter CROSS JOIN pads) WHERE start_ms < end_ms),
{islands_sql('padded', 'pad_ms, source_id', 'w')},
hit AS (SELECT pad_ms, count(DISTINCT event_id) AS n FROM ref r JOIN w ON r.source_id = w.source_id AND r.ts_ms >= w.start_ms AND r.ts_ms < w.end_ms GROUP BY pad_ms)
SELECT CAST(k.pad_ms AS BIGINT) AS pad_ms, CAST(window_ms AS BIGINT) AS window_ms, coalesce(n, 0) AS n_covered FROM (SELECT pad_ms, sum(end_ms - start_ms) AS window_ms FROM w GROUP BY pad_ms) k LEFT JOIN hit ON hit.pad_ms = k.pad_ms""",
    "join_asof": f"""WITH {FOOTAGE_SQL}
SELECT r.source_id, r.event_id, r.ts_ms - (SELECT max(u.start_ms) FROM utter u WHERE u.source_id = r.source_id AND u.start_ms <= r.ts_ms) AS lag_ms FROM ref r""",
}
