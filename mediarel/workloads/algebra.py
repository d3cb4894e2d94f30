"""Every operator of the media algebra on the given tables, through fluent plans."""

from __future__ import annotations

from pyspark.sql import functions as F

from mediarel import measures
from mediarel.functions import geometry
from mediarel.functions.semantic import SemanticFn, call_model, cost_usd
from mediarel.operators import intervals, matching, reconcile
from mediarel.plans import cost
from mediarel.plans.frame import MediaFrame
from mediarel.sources.stored import barrier, representation
from mediarel.workloads import points, spans
from mediarel.workloads.points import PLANS_SQL, islands_sql


def _scan(spark, sf_dir, name):
    return MediaFrame.scan(spark, f"{sf_dir}/{name}.parquet")


def alg_input(spark, sf_dir):
    return _scan(spark, sf_dir, "part").to_df().select("p_partkey", "p_name", "p_brand", "p_type", "p_size")


def alg_map(spark, sf_dir):
    return _scan(spark, sf_dir, "part").derive({"big": F.col("p_size") > 25}).to_df().select("p_partkey", "p_name", "big")


def alg_map_multi(spark, sf_dir):
    plan = _scan(spark, sf_dir, "part").derive({"colour": F.split("p_name", " ")[0], "size_class": "p_size div 10", "dear": "p_retailprice > 1500"})
    return plan.to_df().select("p_partkey", "colour", F.col("size_class").cast("bigint").alias("size_class"), "dear")


def alg_filter(spark, sf_dir):
    return _scan(spark, sf_dir, "events").keep("event_type = 'purchase' AND value >= 120").to_df().select("event_id", "user_id", "value")


def alg_filter_semantic(spark, sf_dir):
    """A semantic predicate: its instruction, a boolean output, and a simulated annotator that looks for junk symbols."""
    fn = SemanticFn("junk", "Is this text junk?", "text", "boolean", lambda df, on, into: df.withColumn(into, F.col(on).rlike(r"[$#&%*]{3}")))
    return _scan(spark, sf_dir, "documents").keep(fn, on="text").to_df().select("doc_id", "n_chars")


def alg_reduce(spark, sf_dir):
    return _scan(spark, sf_dir, "events").fold(["user_id"], {"n": F.count("*"), "top": F.round(F.max("value"), 6)}).to_df()


def alg_reduce_collect(spark, sf_dir):
    kinds = F.concat_ws(",", F.array_sort(F.collect_set("event_type")))
    return _scan(spark, sf_dir, "events").fold(["user_id"], {"kinds": kinds}).to_df()


def alg_reduce_global(spark, sf_dir):
    return _scan(spark, sf_dir, "events").fold([], {"n": F.count("*"), "last_id": F.max("event_id")}).to_df()


def _nested(spark, sf_dir):
    return points.relation(spark, sf_dir)


def alg_unnest(spark, sf_dir):
    return _nested(spark, sf_dir).unnest("t").to_df().select("source_id", "t.event_id", "t.start_ms")


def alg_unnest_outer(spark, sf_dir):
    return _nested(spark, sf_dir).unnest("t", outer=True).to_df().select("source_id", "t.event_id")


def alg_unnest_pos(spark, sf_dir):
    return _nested(spark, sf_dir).unnest("t", ordinal="place").to_df().select("source_id", F.col("place").cast("bigint").alias("place"), "t.event_id")


def _extent(spark, sf_dir):
    """A user's purchases and errors of value 120 or more, as intervals of 30 s."""
    seen = points.footage(spark, sf_dir).where("value >= 120 AND kind IN ('purchase', 'error')")
    return seen.select("source_id", "event_id", "kind", F.col("ts_ms").alias("start_ms"), (F.col("ts_ms") + 30_000).alias("end_ms"))


def _scored(spark, sf_dir):
    both = _extent(spark, sf_dir)
    left = MediaFrame.of(both.where("kind = 'purchase'").select("source_id", F.col("event_id").alias("l"), F.col("start_ms").alias("ls"), F.col("end_ms").alias("le")))
    right = MediaFrame.of(both.where("kind = 'error'").select("source_id", F.col("event_id").alias("r"), F.col("start_ms").alias("rs"), F.col("end_ms").alias("re")))
    score = F.round(geometry.tiou(F.col("ls"), F.col("le"), F.col("rs"), F.col("re")), 6)
    return left.pair(right, ["source_id"], score=score).keep("ls < re AND rs < le")


def alg_join_scored(spark, sf_dir):
    return _scored(spark, sf_dir).to_df().select("source_id", "l", "r", "match_score")


def alg_join_plain(spark, sf_dir):
    users = MediaFrame.of(points.reference(spark, sf_dir).select("source_id", "event_id"))
    told = MediaFrame.of(points.utterances(spark, sf_dir).where("text = 'goal'").select("source_id", F.col("event_id").alias("said_id")))
    return users.pair(told, ["source_id"]).to_df()


def resolve_overlap(spark, sf_dir):
    plan = MediaFrame.of(_extent(spark, sf_dir)).settle(lambda df, within: intervals.coalesce(df, within), ["source_id"])
    return plan.to_df().select("source_id", "window_no", "start_ms", "end_ms")


def resolve_overlap_two_level(spark, sf_dir):
    return intervals.coalesce_two_level(_extent(spark, sf_dir), ["source_id"], 600_000).select("source_id", "window_no", "start_ms", "end_ms")


def resolve_one_to_one(spark, sf_dir):
    plan = _scored(spark, sf_dir).settle(lambda df, within: matching.greedy(df.select("source_id", "l", "r", "match_score"), within, "l", "r", "match_score"), ["source_id"])
    return plan.to_df()


def resolve_one_to_one_rounds(spark, sf_dir):
    """The same matching in distributed rounds."""
    pairs = _scored(spark, sf_dir).to_df().select("source_id", "l", "r", "match_score")
    return matching.mutual_best(pairs, ["source_id"], "l", "r", "match_score")


def resolve_keep_best(spark, sf_dir):
    plan = _scan(spark, sf_dir, "events").settle(lambda df, within: matching.keep_best(df, within, [F.desc("value"), "event_id"]), ["user_id", "event_type"])
    return plan.to_df().select("user_id", "event_type", "event_id")


def resolve_components(spark, sf_dir):
    """Users linked by sharing an hour and an event kind with a high value: closure over pairs."""
    e = points.footage(spark, sf_dir).where("value >= 120 AND kind = 'purchase'").select("source_id", F.expr("ts_ms div 36000").alias("slot")).distinct()
    edges = e.select("slot", F.col("source_id").alias("a")).join(e.select("slot", F.col("source_id").alias("b")), "slot").where("a < b").select("a", "b").distinct()
    return matching.connected_groups(edges).select("node", F.col("group").alias("component"))


def window_pad(spark, sf_dir):
    base = _extent(spark, sf_dir)
    low, high = geometry.pad_window(F.col("start_ms"), F.col("end_ms"), 60_000, 45_000, F.lit(points.DURATION).cast("bigint"))
    return base.select("source_id", "event_id", low.alias("start_ms"), high.alias("end_ms"))


def _hours(spark, sf_dir):
    """Clips of a user by hour, each with the kind of its first event and whether it holds a purchase."""
    first = F.min(F.struct("ts_ms", "event_id", "kind"))["kind"]
    return points.footage(spark, sf_dir).groupBy("source_id", F.expr("ts_ms div 360000").alias("start_ms")).agg(first.alias("label"), F.bool_or(F.col("kind") == "purchase").alias("bought"))


def reconcile_vote(spark, sf_dir):
    """Labels of clips (hours of a user) voted into one label a source."""
    return reconcile.vote("label")(_hours(spark, sf_dir), ["source_id"], "label")


def reconcile_any(spark, sf_dir):
    """A yes on any clip is the source's answer."""
    return reconcile.any_of(_hours(spark, sf_dir), ["source_id"], "bought")


def reconcile_concat(spark, sf_dir):
    """Digests of clips in order of time."""
    return reconcile.concat(_hours(spark, sf_dir), ["source_id"], "label")


def _conflicts(spark, sf_dir):
    """Purchases and clicks of a user at most 15 minutes apart, scored by nearness: many pairs share a side."""
    seen = points.footage(spark, sf_dir)
    left = seen.where("kind = 'purchase'").select("source_id", F.col("event_id").alias("l"), F.col("ts_ms").alias("l_ms"))
    right = seen.where("kind = 'click'").select("source_id", F.col("event_id").alias("r"), F.col("ts_ms").alias("r_ms"))
    pairs = intervals.band_join(left, right, ["source_id"], 900_000, "l_ms", "r_ms")
    return pairs.select("source_id", "l", "r", (-F.abs(F.col("l_ms") - F.col("r_ms"))).cast("double").alias("score"))


def resolve_conflicts(spark, sf_dir):
    """One-to-one settling where nearly every pair has rivals."""
    return matching.greedy(_conflicts(spark, sf_dir), ["source_id"], "l", "r", "score")


def resolve_conflicts_rounds(spark, sf_dir):
    return matching.mutual_best(_conflicts(spark, sf_dir), ["source_id"], "l", "r", "score")


def ablation_stages(spark, sf_dir):
    """What stages of the narrow plan are worth: windows and footage without padding and without coalescing, and matches without one-to-one settling."""
    said, refs = points.utterances(spark, sf_dir), points.reference(spark, sf_dir)
    found = None
    for name, before, after, merged in (("all stages", points.BEFORE, points.AFTER, True), ("no padding", 0, 1, True), ("no coalescing", points.BEFORE, points.AFTER, False)):
        low, high = geometry.pad_window(F.col("start_ms"), F.col("start_ms"), before, after, F.lit(points.DURATION).cast("bigint"))
        cut = said.select("source_id", low.alias("low"), high.alias("end_ms")).select("source_id", F.col("low").alias("start_ms"), "end_ms").where("start_ms < end_ms")
        windows = intervals.coalesce(cut, ["source_id"]).select("source_id", "start_ms", "end_ms") if merged else cut
        covered = intervals.point_join(refs, windows, ["source_id"], 60_000).agg(F.countDistinct("event_id").alias("n_covered"))
        row = windows.agg(F.count("*").alias("n_windows"), F.sum(F.col("end_ms") - F.col("start_ms")).cast("bigint").alias("window_ms")).crossJoin(F.broadcast(covered))
        row = row.select(F.lit(name).alias("variant"), "n_windows", "window_ms", "n_covered")
        found = row if found is None else found.unionByName(row)
    pairs = _conflicts(spark, sf_dir)
    for name, kept in (("no one-to-one", pairs), ("one-to-one", matching.greedy(pairs, ["source_id"], "l", "r", "score"))):
        row = kept.agg(F.count("*").alias("n_windows"), (-F.sum("score")).cast("bigint").alias("window_ms"), F.countDistinct("l").alias("n_covered"))
        found = found.unionByName(row.select(F.lit(name).alias("variant"), "n_windows", "window_ms", "n_covered"))
    return found


def m_tiou(spark, sf_dir):
    return _scored(spark, sf_dir).to_df().select("l", "r", F.col("match_score").alias("tiou"))


def fn_box_iou(spark, sf_dir):
    part = spark.read.parquet(f"{sf_dir}/part.parquet")
    number = lambda c: F.col(c).cast("double")
    a = (number("p_size"), F.lit(0.0), F.lit(20.0), number("p_size"))
    b = (F.lit(15.0), F.lit(5.0), number("p_size"), F.lit(30.0))
    return part.select("p_partkey", F.round(geometry.box_iou(a, b), 6).alias("iou"))


def join_interval(spark, sf_dir):
    both = _extent(spark, sf_dir)
    left = both.where("kind = 'purchase'").select("source_id", F.col("event_id").alias("l"), "start_ms", "end_ms")
    right = both.where("kind = 'error'").select("source_id", F.col("event_id").alias("r"), F.col("start_ms").alias("r_start_ms"), F.col("end_ms").alias("r_end_ms"))
    return intervals.overlap_join(left, right, ["source_id"], 20_000).select("source_id", "l", "r")


def join_interval_dense(spark, sf_dir):
    """Overlapping stays of a user around purchases and clicks, with their temporal IoU: many intervals overlap many."""
    seen = points.footage(spark, sf_dir)
    long = lambda c: (F.col("ts_ms") + c).alias("e")
    left = seen.where("kind = 'purchase'").select("source_id", F.col("event_id").alias("l"), F.col("ts_ms").alias("start_ms"), long(400_000).alias("end_ms"))
    right = seen.where("kind = 'click'").select("source_id", F.col("event_id").alias("r"), F.col("ts_ms").alias("r_start_ms"), long(250_000).alias("r_end_ms"))
    both = intervals.overlap_join(left, right, ["source_id"], 300_000)
    return both.select("source_id", "l", "r", F.round(geometry.tiou(F.col("start_ms"), F.col("end_ms"), F.col("r_start_ms"), F.col("r_end_ms")), 6).alias("tiou"))


def semantic_call(spark, sf_dir):
    """A model asked once for each distinct turn, its answers stored under their keys: a retry or another plan pays nothing again."""
    fn = SemanticFn("asks", "Does this turn ask a question?", "text", "boolean", lambda df, on, into: df)
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "text")
    return call_model(turns, fn, "text", "asks", lambda: lambda texts: ["?" in t for t in texts]).select("conv_id", "turn", "asks", "tokens")


def join_point_in_interval(spark, sf_dir):
    return intervals.point_join(points.reference(spark, sf_dir), points.point_windows(spark, sf_dir), ["source_id"], 30_000).select("source_id", "event_id", "window_no")


def join_band(spark, sf_dir):
    goals = points.reference(spark, sf_dir).select("source_id", "event_id", "ts_ms")
    said = points.utterances(spark, sf_dir).select("source_id", F.col("event_id").alias("said_id"), F.col("start_ms").alias("said_ms"))
    return intervals.band_join(goals, said, ["source_id"], 30_000, "ts_ms", "said_ms").select("source_id", "event_id", "said_id")


def sample_fps(spark, sf_dir):
    from mediarel.operators import media

    return media.sample_fps(points.footage(spark, sf_dir), 1).select("source_id", "event_id")


#: Junk, shouting, or repeated lines: the low-quality test over a representation.
def _low_quality(text):
    lines = F.split(text, "\n")
    return text.rlike(r"[$#&%*]{3}") | text.rlike(r"[A-Z]{4,}!!") | (F.size(F.array_distinct(lines)) / F.size(lines) < 0.7)


def o1_classify_docs(spark, sf_dir):
    """Classification from the full text and from its head: one task, two representations."""
    head = SemanticFn("low quality", "Is this of low quality?", "head", "boolean", lambda df, on, into: df.withColumn(into, _low_quality(F.col(on))))
    full = SemanticFn("low quality", "Is this of low quality?", "text", "boolean", lambda df, on, into: df.withColumn(into, _low_quality(F.col(on))), siblings={"head": head})
    from mediarel.plans.rules import SubstituteModality

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", F.substring("text", 1, 200).alias("head"))
    plan = MediaFrame.of(docs).derive({"low": full}, on="text")
    heavy = plan.to_df().select("doc_id", F.col("low").alias("low_full"))
    light = plan.rewrite(SubstituteModality("text", "head")).to_df().select("doc_id", F.col("low").alias("low_head"))
    return heavy.join(light, "doc_id")


def o1_classify_prf(spark, sf_dir):
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", (F.col("quality") == 0).alias("bad"))
    told = o1_classify_docs(spark, sf_dir).join(labels, "doc_id")
    flat = told.select("bad", F.explode(F.create_map(F.lit("full"), F.col("low_full"), F.lit("head"), F.col("low_head"))).alias("plan", "low"))
    return flat.groupBy("plan").agg(F.count_if(F.col("low") & F.col("bad")).alias("tp"), F.count_if(F.col("low") & ~F.col("bad")).alias("fp"), F.count_if("bad").alias("n_ref"))


def o1_extract_pages(spark, sf_dir):
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    return pages.select("page_id", F.regexp_extract("html", r'<html lang="([a-z]+)"', 1).alias("lang_html"), F.regexp_extract("url", r"/([a-z]{2})/", 1).alias("lang_url"))


def o1_extract_agreement(spark, sf_dir):
    return o1_extract_pages(spark, sf_dir).agg(F.count("*").alias("n"), F.count_if(F.col("lang_html") == F.col("lang_url")).alias("n_same"))


def o1_summarize_conv(spark, sf_dir):
    """A digest from the first sentence of every turn, and from the opening user turn alone."""
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet").withColumn("first", F.regexp_extract("text", r"^[^.!?]*[.!?]?", 0))
    whole = F.concat_ws(" ", F.transform(F.array_sort(F.collect_list(F.struct("turn", "first"))), lambda x: x["first"]))
    opening = F.min(F.when(F.col("role") == "user", F.struct("turn", "first")))["first"]
    return turns.groupBy("conv_id").agg(F.md5(whole).alias("digest_md5"), F.md5(opening).alias("opening_md5"))


def o1_reuse_materialized(spark, sf_dir):
    """A second task on the stored transcript: it is made and stored by the first reader and read by all others, never the footage."""
    kind = "struct<source_id:bigint,event_id:bigint,start_ms:bigint,text:string>"
    said = representation(spark, "utterances", "1", f"{sf_dir}/events.parquet", lambda: points.utterances(spark, sf_dir)).select(F.struct("*").cast(kind).alias("u")).select("u.*")
    counts = said.groupBy("source_id").agg(F.count("*").alias("n_said"), F.count_if(F.col("text") == "goal").alias("n_goal"))
    zero = lambda c: F.coalesce(c, F.lit(0).cast("bigint")).alias(c)
    return points.sources(spark, sf_dir).select("source_id").join(counts, "source_id", "left").select("source_id", zero("n_said"), zero("n_goal"))


_WORKLOADS = (("points", points, 30_000), ("spans", spans, 0.3))


def plan_cost_table(spark, sf_dir):
    """Share of footage watched, calls, tokens, money and accuracy of each plan of both event workloads, from the ledgers of their runs."""
    found = None
    for workload, module, at in _WORKLOADS:
        preds = paid = None
        for name, plan in module.PLANS.items():
            done, ledger = plan(spark, sf_dir).metered()
            rows, sums = module.told(done).withColumn("plan", F.lit(name)), ledger.withColumn("plan", F.lit(name))
            preds, paid = (rows, sums) if preds is None else (preds.unionByName(rows), paid.unionByName(sums))
        whole = module.sources(spark, sf_dir).agg(F.sum("duration_ms").alias("source_ms"))
        costs = paid.groupBy("plan").agg(F.sum("calls").alias("calls"), F.sum("tokens").alias("tokens"), F.sum("watched_ms").alias("watched_ms")).crossJoin(F.broadcast(whole))
        ref, preds = module.reference(spark, sf_dir), barrier(preds)
        curve = measures.point_curve(preds, ref, (at,)) if module is points else measures.span_curve(preds, ref, (at,), ("source_id", "task_id"))
        rows = costs.join(curve, "plan").select(
            F.lit(workload).alias("workload"), "plan", F.round(100 * F.col("watched_ms") / F.col("source_ms"), 4).alias("video_pct"), "calls", "tokens", cost_usd(F.col("tokens")).alias("cost_usd"), "precision", "recall", "f1"
        )
        found = rows if found is None else found.unionByName(rows)
    return found


LEAST_RECALL = 0.9


def plan_choice(spark, sf_dir):
    """The cheapest plan of each workload that reaches the recall, chosen from the costs and accuracies that the runs measured."""
    held: dict[str, list[cost.Estimate]] = {}
    # Three rows a workload.
    for r in plan_cost_table(spark, sf_dir).collect():
        held.setdefault(r["workload"], []).append(cost.Estimate(r["plan"], r["tokens"], r["recall"]))
    chosen = [(w, cost.choose(found, LEAST_RECALL)) for w, found in sorted(held.items())]
    return spark.createDataFrame([(w, e.plan, int(e.tokens), e.recall) for w, e in chosen], "workload string, plan string, tokens bigint, recall double")


def plan_times(spark, sf_dir):
    """Cold-start seconds and rows of each component of every plan; stored transcripts are not counted, as in the published table."""
    rows = []
    for workload, module, _ in _WORKLOADS:
        for name, plan in module.PLANS.items():
            rows += [(workload, name, k, part, round(seconds, 3), held) for k, (part, seconds, held) in enumerate(plan(spark, sf_dir).timed()[1])]
    return spark.createDataFrame(rows, "workload string, plan string, step int, component string, seconds double, n_rows bigint")


def _table_pairs(spark, sf_dir):
    """Candidate pairs of tracks: a supplier is a camera, a part it ships is a track from first to last shipping date."""
    read = lambda t: spark.read.parquet(f"{sf_dir}/{t}.parquet")
    tracks = read("lineitem").groupBy("l_suppkey", "l_partkey").agg(F.min(F.to_date("l_shipdate")).alias("first"), F.max(F.to_date("l_shipdate")).alias("last"))
    placed = tracks.join(read("supplier").select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").alias("scene")), "l_suppkey").join(read("part").select(F.col("p_partkey").alias("l_partkey"), "p_brand", "p_type"), "l_partkey")
    day = lambda c: F.datediff(c, F.lit("1970-01-01")).cast("bigint")
    flat = placed.select("scene", "p_brand", "p_type", "l_suppkey", "l_partkey", day(F.col("first")).alias("b"), (day(F.col("last")) + 1).alias("e"))
    left = flat.select("scene", "p_brand", "p_type", F.col("l_suppkey").alias("left_source"), F.col("l_partkey").alias("l"), F.col("b").alias("start_ms"), F.col("e").alias("end_ms"))
    right = flat.select("scene", "p_brand", "p_type", F.col("l_suppkey").alias("right_source"), F.col("l_partkey").alias("r"), F.col("b").alias("r_start_ms"), F.col("e").alias("r_end_ms"))
    pairs = intervals.overlap_join(left, right, ["scene", "p_brand", "p_type"], 365).where("left_source < right_source")
    return pairs.withColumn("match_score", F.round(geometry.tiou(F.col("start_ms"), F.col("end_ms"), F.col("r_start_ms"), F.col("r_end_ms")), 6))


def xcam_tables(spark, sf_dir):
    """The staged join at table scale up to its candidates: pairs and best score of every two suppliers."""
    return _table_pairs(spark, sf_dir).groupBy("left_source", "right_source").agg(F.count("*").alias("n_pairs"), F.round(F.max("match_score"), 6).alias("best"))


def xcam_tables_settled(spark, sf_dir):
    """The whole staged join at table scale: the candidates of every two suppliers settled one to one by overlap score."""
    pairs = _table_pairs(spark, sf_dir).select("left_source", "right_source", "l", "r", "match_score")
    return matching.mutual_best(pairs, ["left_source", "right_source"], "l", "r", "match_score")


EXTENT_SQL = f"""{PLANS_SQL},
ext AS (SELECT source_id, event_id, kind, ts_ms AS start_ms, ts_ms + 30000 AS end_ms FROM footage WHERE value >= 120 AND kind IN ('purchase', 'error')),
sc AS (
  SELECT l.source_id, l.event_id AS l, r.event_id AS r, round((least(l.end_ms, r.end_ms) - greatest(l.start_ms, r.start_ms)) / (60000 - (least(l.end_ms, r.end_ms) - greatest(l.start_ms, r.start_ms))), 6) AS match_score
  FROM ext l JOIN ext r ON l.source_id = r.source_id AND l.kind = 'purchase' AND r.kind = 'error' AND l.start_ms < r.end_ms AND r.start_ms < l.end_ms)"""
_ONE_TO_ONE = f"""WITH RECURSIVE {EXTENT_SQL},
k AS (SELECT *, row_number() OVER (PARTITION BY source_id ORDER BY match_score DESC, l, r) AS p FROM sc),
w AS (
  SELECT source_id, l, r, match_score, p, TRUE AS kept, [l] AS ul, [r] AS ur FROM k WHERE p = 1
  UNION ALL SELECT k.source_id, k.l, k.r, k.match_score, k.p, NOT (list_contains(ul, k.l) OR list_contains(ur, k.r)),
    CASE WHEN list_contains(ul, k.l) OR list_contains(ur, k.r) THEN ul ELSE list_append(ul, k.l) END, CASE WHEN list_contains(ul, k.l) OR list_contains(ur, k.r) THEN ur ELSE list_append(ur, k.r) END
  FROM w JOIN k ON k.source_id = w.source_id AND k.p = w.p + 1)
SELECT source_id, l, r, match_score FROM w WHERE kept"""
_PAIRS = f"""{PLANS_SQL},
cp AS (SELECT l.source_id, l.event_id AS l, r.event_id AS r, CAST(-abs(l.ts_ms - r.ts_ms) AS DOUBLE) AS score FROM footage l JOIN footage r ON l.source_id = r.source_id AND l.kind = 'purchase' AND r.kind = 'click' AND abs(l.ts_ms - r.ts_ms) <= 900000)"""
_SETTLED = f"""{_PAIRS},
ck AS (SELECT *, row_number() OVER (PARTITION BY source_id ORDER BY score DESC, l, r) AS p FROM cp),
cw AS (
  SELECT source_id, l, r, score, p, TRUE AS kept, [l] AS ul, [r] AS ur FROM ck WHERE p = 1
  UNION ALL SELECT ck.source_id, ck.l, ck.r, ck.score, ck.p, NOT (list_contains(ul, ck.l) OR list_contains(ur, ck.r)),
    CASE WHEN list_contains(ul, ck.l) OR list_contains(ur, ck.r) THEN ul ELSE list_append(ul, ck.l) END, CASE WHEN list_contains(ul, ck.l) OR list_contains(ur, ck.r) THEN ur ELSE list_append(ur, ck.r) END
  FROM cw JOIN ck ON ck.source_id = cw.source_id AND ck.p = cw.p + 1)"""
_CONFLICTS = f"WITH RECURSIVE {_SETTLED} SELECT source_id, l, r, score FROM cw WHERE kept"
_HOURS = f"""{PLANS_SQL},
hour AS (SELECT source_id, ts_ms // 360000 AS hr, arg_min(kind, ts_ms * 10000000 + event_id) AS label, bool_or(kind = 'purchase') AS bought FROM footage GROUP BY ALL)"""
_OVERLAP = f"WITH {EXTENT_SQL}, {islands_sql('ext', 'source_id', 'm')} SELECT source_id, window_no, start_ms, end_ms FROM m"
_LOW_SQL = "(regexp_matches({t}, '[$#&%*]{{3}}') OR regexp_matches({t}, '[A-Z]{{4,}}!!') OR len(list_distinct(string_split({t}, chr(10)))) / len(string_split({t}, chr(10))) < 0.7)"
_CLASSIFY = f"SELECT doc_id, {_LOW_SQL.format(t='text')} AS low_full, {_LOW_SQL.format(t='substr(text, 1, 200)')} AS low_head FROM documents"

QUERIES = {
    f.__name__: f
    for f in (
        alg_input, alg_map, alg_map_multi, alg_filter, alg_filter_semantic, alg_reduce, alg_reduce_collect, alg_reduce_global, alg_unnest, alg_unnest_outer, alg_unnest_pos,
        alg_join_scored, alg_join_plain, resolve_overlap, resolve_overlap_two_level, resolve_one_to_one, resolve_one_to_one_rounds, resolve_keep_best, resolve_components,
        window_pad, reconcile_vote, m_tiou, fn_box_iou, join_interval, join_point_in_interval, join_band, sample_fps, o1_classify_docs, o1_classify_prf, o1_extract_pages,
        o1_extract_agreement, o1_summarize_conv, o1_reuse_materialized, plan_cost_table, xcam_tables,
        xcam_tables_settled, reconcile_any, reconcile_concat, resolve_conflicts, resolve_conflicts_rounds, ablation_stages, plan_times, plan_choice, join_interval_dense, semantic_call,
    )
}

ORACLE_SQL = {
    "alg_input": "SELECT p_partkey, p_name, p_brand, p_type, p_size FROM part",
    "alg_map": "SELECT p_partkey, p_name, p_size > 25 AS big FROM part",
    "alg_map_multi": "SELECT p_partkey, split_part(p_name, ' ', 1) AS colour, CAST(p_size // 10 AS BIGINT) AS size_class, p_retailprice > 1500 AS dear FROM part",
    "alg_filter": "SELECT event_id, user_id, value FROM events WHERE event_type = 'purchase' AND value >= 120",
    "alg_filter_semantic": "SELECT doc_id, n_chars FROM documents WHERE regexp_matches(text, '[$#&%*]{3}')",
    "alg_reduce": "SELECT user_id, count(*) AS n, round(max(value), 6) AS top FROM events GROUP BY user_id",
    "alg_reduce_collect": "SELECT user_id, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS kinds FROM events GROUP BY user_id",
    "alg_reduce_global": "SELECT count(*) AS n, max(event_id) AS last_id FROM events",
    "alg_unnest": f"WITH {PLANS_SQL} SELECT source_id, event_id, start_ms FROM utter",
    "alg_unnest_outer": f"WITH {PLANS_SQL} SELECT s.source_id, u.event_id FROM sources s LEFT JOIN utter u ON s.source_id = u.source_id",
    "alg_unnest_pos": f"WITH {PLANS_SQL} SELECT source_id, row_number() OVER (PARTITION BY source_id ORDER BY start_ms, event_id) - 1 AS place, event_id FROM utter",
    "alg_join_scored": f"WITH {EXTENT_SQL} SELECT source_id, l, r, match_score FROM sc",
    "alg_join_plain": f"WITH {PLANS_SQL} SELECT r.source_id, r.event_id, u.event_id AS said_id FROM ref r JOIN utter u ON r.source_id = u.source_id WHERE u.text = 'goal'",
    "resolve_overlap": _OVERLAP,
    "resolve_overlap_two_level": _OVERLAP,
    "resolve_one_to_one": _ONE_TO_ONE,
    "resolve_one_to_one_rounds": _ONE_TO_ONE,
    "resolve_conflicts": _CONFLICTS,
    "resolve_conflicts_rounds": _CONFLICTS,
    "reconcile_any": f"WITH {_HOURS} SELECT source_id, bool_or(bought) AS bought FROM hour GROUP BY source_id",
    "reconcile_concat": f"WITH {_HOURS} SELECT source_id, string_agg(label, ' ' ORDER BY hr) AS label FROM hour GROUP BY source_id",
    "ablation_stages": f"""WITH RECURSIVE {_SETTLED},
bare AS (SELECT source_id, start_ms, least(start_ms + 1, 4320000) AS end_ms FROM utter WHERE start_ms < 4320000),
{islands_sql('bare', 'source_id', 'bw')}
SELECT 'all stages' AS variant, count(*) AS n_windows, CAST(sum(end_ms - start_ms) AS BIGINT) AS window_ms, (SELECT count(DISTINCT event_id) FROM ref r JOIN windows w ON r.source_id = w.source_id AND ts_ms >= start_ms AND ts_ms < end_ms) AS n_covered FROM windows
UNION ALL SELECT 'no padding', count(*), CAST(sum(end_ms - start_ms) AS BIGINT), (SELECT count(DISTINCT event_id) FROM ref r JOIN bw w ON r.source_id = w.source_id AND ts_ms >= start_ms AND ts_ms < end_ms) FROM bw
UNION ALL SELECT 'no coalescing', count(*), CAST(sum(end_ms - start_ms) AS BIGINT), (SELECT count(DISTINCT r.event_id) FROM ref r JOIN cand w ON r.source_id = w.source_id AND ts_ms >= w.start_ms AND ts_ms < w.end_ms) FROM cand
UNION ALL SELECT 'no one-to-one', count(*), CAST(-sum(score) AS BIGINT), count(DISTINCT l) FROM cp
UNION ALL SELECT 'one-to-one', count(*), CAST(-sum(score) AS BIGINT), count(DISTINCT l) FROM cw WHERE kept""",
    "resolve_keep_best": "SELECT user_id, event_type, event_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id, event_type ORDER BY value DESC, event_id) AS k FROM events) WHERE k = 1",
    "resolve_components": f"""WITH RECURSIVE {PLANS_SQL},
e AS (SELECT DISTINCT source_id, ts_ms // 36000 AS slot FROM footage WHERE value >= 120 AND kind = 'purchase'),
g AS (SELECT DISTINCT a.source_id AS a, b.source_id AS b FROM e a JOIN e b ON a.slot = b.slot AND a.source_id <> b.source_id),
w AS (SELECT DISTINCT a AS node, a AS root FROM g UNION SELECT g.b, w.root FROM w JOIN g ON g.a = w.node)
SELECT node, min(root) AS component FROM w GROUP BY node""",
    "window_pad": f"WITH {EXTENT_SQL} SELECT source_id, event_id, greatest(start_ms - 60000, 0) AS start_ms, least(end_ms + 45000, 4320000) AS end_ms FROM ext",
    "reconcile_vote": f"""WITH {PLANS_SQL},
c AS (SELECT source_id, kind AS label FROM (SELECT *, row_number() OVER (PARTITION BY source_id, ts_ms // 360000 ORDER BY ts_ms, event_id) AS k FROM footage) WHERE k = 1),
n AS (SELECT source_id, label, count(*) AS n FROM c GROUP BY ALL)
SELECT source_id, label FROM (SELECT *, row_number() OVER (PARTITION BY source_id ORDER BY n DESC, label) AS k FROM n) WHERE k = 1""",
    "m_tiou": f"WITH {EXTENT_SQL} SELECT l, r, match_score AS tiou FROM sc",
    "fn_box_iou": """WITH b AS (SELECT p_partkey, CAST(p_size AS DOUBLE) AS s, greatest(least(s + 20, 15 + s) - greatest(s, 15), 0) * greatest(least(s, 35) - 5, 0) AS i FROM part)
SELECT p_partkey, round(CASE WHEN 20 * s + 30 * s - i > 0 THEN i / (20 * s + 30 * s - i) ELSE 0 END, 6) AS iou FROM b""",
    "join_interval_dense": f"""WITH {PLANS_SQL},
o AS (SELECT l.source_id, l.event_id AS l, r.event_id AS r, least(l.ts_ms + 400000, r.ts_ms + 250000) - greatest(l.ts_ms, r.ts_ms) AS ms FROM footage l JOIN footage r ON l.source_id = r.source_id AND l.kind = 'purchase' AND r.kind = 'click' AND l.ts_ms < r.ts_ms + 250000 AND r.ts_ms < l.ts_ms + 400000)
SELECT source_id, l, r, round(ms / (650000 - ms), 6) AS tiou FROM o""",
    "semantic_call": "SELECT conv_id, turn, contains(text, '?') AS asks, CAST(length(text) // 4 + 1 AS BIGINT) AS tokens FROM conversations",
    "join_interval": f"WITH {EXTENT_SQL} SELECT source_id, l, r FROM sc",
    "join_point_in_interval": f"WITH {PLANS_SQL} SELECT r.source_id, event_id, window_no FROM ref r JOIN windows w ON r.source_id = w.source_id AND ts_ms >= start_ms AND ts_ms < end_ms",
    "join_band": f"WITH {PLANS_SQL} SELECT r.source_id, r.event_id, u.event_id AS said_id FROM ref r JOIN utter u ON r.source_id = u.source_id AND abs(r.ts_ms - u.start_ms) <= 30000",
    "sample_fps": f"WITH {PLANS_SQL} SELECT source_id, event_id FROM (SELECT *, row_number() OVER (PARTITION BY source_id, ts_ms // 1000 ORDER BY ts_ms, event_id) AS k FROM footage) WHERE k = 1",
    "o1_classify_docs": _CLASSIFY,
    "o1_classify_prf": f"""WITH d AS (SELECT quality = 0 AS bad, x.* FROM ({_CLASSIFY}) x JOIN labels l ON l.doc_id = x.doc_id)
SELECT 'full' AS plan, count(*) FILTER (low_full AND bad) AS tp, count(*) FILTER (low_full AND NOT bad) AS fp, count(*) FILTER (bad) AS n_ref FROM d
UNION ALL SELECT 'head', count(*) FILTER (low_head AND bad), count(*) FILTER (low_head AND NOT bad), count(*) FILTER (bad) FROM d""",
    "o1_extract_pages": "SELECT page_id, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS lang_html, regexp_extract(url, '/([a-z]{2})/', 1) AS lang_url FROM pages",
    "o1_extract_agreement": "SELECT count(*) AS n, count(*) FILTER (regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) = regexp_extract(url, '/([a-z]{2})/', 1)) AS n_same FROM pages",
    "o1_summarize_conv": """WITH t AS (SELECT conv_id, turn, role, regexp_extract(text, '^[^.!?]*[.!?]?', 0) AS f FROM conversations)
SELECT conv_id, md5(string_agg(f, ' ' ORDER BY turn)) AS digest_md5, md5(arg_min(f, turn) FILTER (role = 'user')) AS opening_md5 FROM t GROUP BY conv_id""",
    "o1_reuse_materialized": f"WITH {PLANS_SQL} SELECT s.source_id, count(u.event_id) AS n_said, count(u.event_id) FILTER (u.text = 'goal') AS n_goal FROM sources s LEFT JOIN utter u ON s.source_id = u.source_id GROUP BY s.source_id",
    "plan_cost_table": f"""WITH pc AS ({points.ORACLE_SQL['m_point_curve']}), sc AS ({spans.ORACLE_SQL['m_span_curve']}),
pw AS ({points.ORACLE_SQL['point_windows']}), sw AS ({spans.ORACLE_SQL['span_windows']}),
base AS (
  SELECT 'points' AS workload, d.*, c.* FROM (SELECT count(*) AS sources, sum(ms) AS source_ms, sum(CAST(ceil(ms * 91 / 1000) AS BIGINT)) AS f, sum(CAST(ceil(ms * 85 / 10000) AS BIGINT)) AS n FROM (SELECT DISTINCT user_id, 4320000 AS ms FROM events)) d
  CROSS JOIN (SELECT count(*) AS clips, sum(end_ms - start_ms) AS window_ms, sum(CAST(ceil((end_ms - start_ms) * 91 / 1000) AS BIGINT)) AS c FROM pw) c
  UNION ALL
  SELECT 'spans', d.*, c.* FROM (SELECT count(*), sum(ms), sum(CAST(ceil(ms * 91 / 1000) AS BIGINT)), sum(CAST(ceil(ms * 85 / 10000) AS BIGINT)) FROM (SELECT n_chars * 50 AS ms FROM documents)) d
  CROSS JOIN (SELECT count(*), sum(end_ms - start_ms), sum(CAST(ceil((end_ms - start_ms) * 91 / 1000) AS BIGINT)) FROM sw) c),
plans AS (
  SELECT workload, 'direct' AS plan, 1.0 AS share, sources AS calls, f AS tokens FROM base UNION ALL SELECT workload, 'narration', 0.0, sources, n FROM base
  UNION ALL SELECT workload, 'narrow', window_ms / source_ms, sources + clips, n + c FROM base),
acc AS (SELECT 'points' AS workload, plan, precision, recall, f1 FROM pc WHERE threshold = 30000 UNION ALL SELECT 'spans', plan, precision, recall, f1 FROM sc WHERE threshold = 0.3)
SELECT p.workload, p.plan, round(CAST(100 * share AS DOUBLE), 4) AS video_pct, CAST(calls AS BIGINT) AS calls, CAST(tokens AS BIGINT) AS tokens, round(CAST(tokens AS DOUBLE) * 0.25 / 1000000, 6) AS cost_usd, precision, recall, f1 FROM plans p JOIN acc USING (workload, plan)""",
    "xcam_tables": """WITH t AS (SELECT l_suppkey, l_partkey, date_diff('day', DATE '1970-01-01', CAST(min(l_shipdate) AS DATE)) AS b, date_diff('day', DATE '1970-01-01', CAST(max(l_shipdate) AS DATE)) + 1 AS e FROM lineitem GROUP BY ALL),
p AS (SELECT t.*, s_nationkey AS scene, p_brand, p_type FROM t JOIN supplier ON s_suppkey = l_suppkey JOIN part ON p_partkey = l_partkey)
SELECT l.l_suppkey AS left_source, r.l_suppkey AS right_source, count(*) AS n_pairs, round(max((least(l.e, r.e) - greatest(l.b, r.b)) / (l.e - l.b + r.e - r.b - (least(l.e, r.e) - greatest(l.b, r.b)))), 6) AS best
FROM p l JOIN p r ON l.scene = r.scene AND l.p_brand = r.p_brand AND l.p_type = r.p_type AND l.l_suppkey < r.l_suppkey AND l.b < r.e AND r.b < l.e GROUP BY ALL""",
    "xcam_tables_settled": """WITH RECURSIVE t AS (SELECT l_suppkey, l_partkey, date_diff('day', DATE '1970-01-01', CAST(min(l_shipdate) AS DATE)) AS b, date_diff('day', DATE '1970-01-01', CAST(max(l_shipdate) AS DATE)) + 1 AS e FROM lineitem GROUP BY ALL),
p AS (SELECT t.*, s_nationkey AS scene, p_brand, p_type FROM t JOIN supplier ON s_suppkey = l_suppkey JOIN part ON p_partkey = l_partkey),
sc AS (
  SELECT l.l_suppkey AS left_source, r.l_suppkey AS right_source, l.l_partkey AS l, r.l_partkey AS r,
    round((least(l.e, r.e) - greatest(l.b, r.b)) / (l.e - l.b + r.e - r.b - (least(l.e, r.e) - greatest(l.b, r.b))), 6) AS match_score
  FROM p l JOIN p r ON l.scene = r.scene AND l.p_brand = r.p_brand AND l.p_type = r.p_type AND l.l_suppkey < r.l_suppkey AND l.b < r.e AND r.b < l.e),
k AS (SELECT *, row_number() OVER (PARTITION BY left_source, right_source ORDER BY match_score DESC, l, r) AS p FROM sc),
w AS (
  SELECT left_source, right_source, l, r, match_score, p, TRUE AS kept, [l] AS ul, [r] AS ur FROM k WHERE p = 1
  UNION ALL SELECT k.left_source, k.right_source, k.l, k.r, k.match_score, k.p, NOT (list_contains(ul, k.l) OR list_contains(ur, k.r)),
    CASE WHEN list_contains(ul, k.l) OR list_contains(ur, k.r) THEN ul ELSE list_append(ul, k.l) END, CASE WHEN list_contains(ul, k.l) OR list_contains(ur, k.r) THEN ur ELSE list_append(ur, k.r) END
  FROM w JOIN k ON k.left_source = w.left_source AND k.right_source = w.right_source AND k.p = w.p + 1)
SELECT left_source, right_source, l, r, match_score FROM w WHERE kept""",
}
ORACLE_SQL["plan_choice"] = f"""SELECT workload, plan, tokens, recall FROM (
  SELECT *, row_number() OVER (PARTITION BY workload ORDER BY tokens, recall DESC, plan) AS k FROM ({ORACLE_SQL["plan_cost_table"]}) WHERE recall >= 0.9) WHERE k = 1"""
