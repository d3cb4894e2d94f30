"""Laws, golden measures, rewrites and plans of the media algebra."""

import random
import shutil

import numpy as np
import pytest
from pyspark.sql import functions as F

from mediarel import measures
from mediarel.functions.semantic import SemanticFn, call_model, compose
from mediarel.operators import intervals, matching, reconcile, vision
from mediarel.plans import cost, ir
from mediarel.plans.frame import MediaFrame
from mediarel.plans.rules import OrderFilters, PushdownWindows, SubstituteModality
from mediarel.workloads import catalog, points, relational, spans

#: Published counts (true positives, predictions, references) and the F1 printed for them.
GOLDEN = [(9, 12, 10, 0.818), (8, 11, 10, 0.762), (9, 11, 10, 0.857), (10, 11, 10, 0.952), (3, 4, 4, 0.75), (2, 4, 4, 0.5), (1, 4, 4, 0.25), (3, 3, 4, 0.857), (1, 3, 4, 0.286), (0, 3, 4, 0.0), (4, 5, 4, 0.889), (2, 5, 4, 0.444), (4, 4, 18, 0.364), (13, 14, 18, 0.813)]


@pytest.mark.parametrize(("tp", "n_pred", "n_ref", "f1"), GOLDEN)
def test_golden_f1(tp, n_pred, n_ref, f1):
    assert measures.f1_of(tp, n_pred, n_ref)[2] == pytest.approx(f1, abs=6e-4)


def test_undefined_measures_are_none():
    assert measures.f1_of(0, 0, 0) == (None, None, None)


def test_published_reductions_and_token_model():
    assert measures.reduction(712.3, 135.8) == pytest.approx(0.809, abs=1e-3)
    assert measures.reduction(1.506, 0.217) == pytest.approx(0.856, abs=1e-3)
    assert cost.tokens("narrow", 16_522, 879 / 16_522) == pytest.approx(0.217e6, rel=0.05)
    assert cost.tokens("direct", 14_115) == pytest.approx(1.285e6, rel=0.01)
    assert 0.9 < cost.break_even_selectivity() < 0.92


def test_choice_follows_recall_then_cost():
    plans = [cost.Estimate("direct", 100, 0.9), cost.Estimate("narration", 10, 0.7), cost.Estimate("narrow", 20, 0.95)]
    assert cost.choose(plans, 0.9).plan == "narrow"
    assert cost.choose(plans, 0.5).plan == "narration"
    with pytest.raises(ValueError, match="no plan"):
        cost.choose(plans, 0.99)


def _random_spans(spark, seed, n=300):
    rng = random.Random(seed)
    rows = [(rng.randrange(5), s, s + rng.randrange(1, 40)) for s in (rng.randrange(0, 1000) for _ in range(n))]
    return rows, spark.createDataFrame(rows, "source_id bigint, start_ms bigint, end_ms bigint")


@pytest.mark.parametrize("seed", [1, 2])
def test_coalesce_against_millisecond_sets(spark, seed):
    rows, df = _random_spans(spark, seed, 60)
    merged = intervals.coalesce(df, ["source_id"]).orderBy("source_id", "start_ms").collect()
    for source in range(5):
        covered = {t for s, a, b in rows if s == source for t in range(a, b)}
        mine = [(r.start_ms, r.end_ms) for r in merged if r.source_id == source]
        assert {t for a, b in mine for t in range(a, b)} == covered
        assert all(x[1] <= y[0] for x, y in zip(mine, mine[1:]))
    again = intervals.coalesce(intervals.coalesce(df, ["source_id"]), ["source_id"])
    assert sorted(map(tuple, again.select("source_id", "start_ms", "end_ms").collect())) == sorted((r.source_id, r.start_ms, r.end_ms) for r in merged)
    two = intervals.coalesce_two_level(df, ["source_id"], 64)
    assert sorted(map(tuple, two.select("source_id", "start_ms", "end_ms").collect())) == sorted((r.source_id, r.start_ms, r.end_ms) for r in merged)


def test_touching_windows_stay_apart_unless_asked(spark):
    df = spark.createDataFrame([(1, 0, 10), (1, 10, 20)], "source_id bigint, start_ms bigint, end_ms bigint")
    assert intervals.coalesce(df, ["source_id"]).count() == 2
    assert intervals.coalesce(df, ["source_id"], touching=True).count() == 1


def test_joins_against_brute_force(spark):
    rows, df = _random_spans(spark, 7, 80)
    other, right = _random_spans(spark, 8, 80)
    joined = intervals.overlap_join(df, right.toDF("source_id", "r_start_ms", "r_end_ms"), ["source_id"], 16)
    brute = [(s, a, b, c, d) for s, a, b in rows for t, c, d in other if s == t and a < d and c < b]
    assert sorted(map(tuple, joined.select("source_id", "start_ms", "end_ms", "r_start_ms", "r_end_ms").collect())) == sorted(brute)
    band = intervals.band_join(df.select("source_id", "start_ms"), right.select("source_id", F.col("start_ms").alias("o")), ["source_id"], 9, "start_ms", "o")
    assert band.count() == sum(s == t and abs(a - c) <= 9 for s, a, _ in rows for t, c, _ in other)


def test_rounds_equal_greedy(spark):
    rng = random.Random(3)
    rows = [(g, a, b, round(rng.random(), 1)) for g in range(3) for a in range(8) for b in range(8)]
    df = spark.createDataFrame(rows, "g int, l bigint, r bigint, score double")
    one = sorted(map(tuple, matching.greedy(df, ["g"], "l", "r", "score").collect()))
    two = sorted(map(tuple, matching.mutual_best(df, ["g"], "l", "r", "score").collect()))
    assert one == two
    assert len({(g, a) for g, a, _, _ in one}) == len(one) == len({(g, b) for g, _, b, _ in one})


def test_connected_groups(spark):
    edges = [(i, i + 1) for i in range(20)] + [(100, 101), (50, 52)]
    found = dict(map(tuple, matching.connected_groups(spark.createDataFrame(edges, "a bigint, b bigint")).collect()))
    assert all(found[i] == 0 for i in range(21)) and found[101] == 100 and found[52] == 50


def test_suppression_and_tracking():
    box = lambda i, f, x, conf: {"det_id": i, "frame_no": f, "x": x, "y": 0.0, "w": 50.0, "h": 40.0, "conf": conf, "cls": "a", "colour": "red", "subtype": "s", "emb": [1.0, 0.0]}
    kept = vision.suppress([box(1, 0, 0, 0.6), box(2, 0, 4, 0.9), box(3, 0, 200, 0.5)])
    assert [b["det_id"] for b in kept] == [2, 3]
    dets = [box(f, f, 10.0 * f, 0.9) for f in range(20) if f not in (5, 11)] + [box(100 + f, f, 500.0, 0.9) for f in range(2)]
    tracks = vision.MotionTracker().tracks(dets)
    assert [(t["first_frame"], t["last_frame"], t["n_det"]) for t in tracks] == [(0, 19, 18)]


def test_chunked_tracking_stitches(spark):
    box = lambda f: {"det_id": f, "frame_no": f, "x": 10.0 * f, "y": 0.0, "w": 50.0, "h": 40.0, "conf": 0.9, "cls": "a", "colour": "red", "subtype": "s", "emb": [1.0]}
    pieces = []
    for chunk in (0, 1, 2):
        for t in vision.MotionTracker().tracks([box(f) for f in range(chunk * 10, chunk * 10 + 10)]):
            pieces.append((1, chunk, t["track_id"], t["first_frame"], t["last_frame"], t["first_x"], t["first_y"], t["last_x"], t["last_y"], t["w"], t["h"], t["vx"], t["vy"], t["cls"]))
    df = spark.createDataFrame(pieces, "source_id bigint, chunk int, track_id bigint, first_frame int, last_frame int, first_x double, first_y double, last_x double, last_y double, w double, h double, vx double, vy double, cls string")
    assert sorted((r.chunk, r.l_track_id, r.r_track_id) for r in vision.stitch(df).collect()) == [(0, 0, 0), (1, 0, 0)]


def test_rules_refuse(spark, sf_dir):
    plan = points.direct(spark, sf_dir)
    base = points.task(spark, sf_dir)
    never = SemanticFn("never", "Does it never happen?", "v", base.output, base.run, witness="global")
    with pytest.raises(ir.PlanError, match="whole source"):
        points.relation(spark, sf_dir).derive({"events": never}, on="v").rewrite(PushdownWindows(points.candidates_fn(), "t", 0, 0, reconcile.points()))
    with pytest.raises(ir.PlanError, match="no form"):
        plan.rewrite(SubstituteModality("v", "audio"))
    odd = SemanticFn("odd", "x", "v", base.output, base.run, siblings={"t": SemanticFn("y", "y", "t", "string", base.run)})
    with pytest.raises(ir.PlanError, match="another schema"):
        points.relation(spark, sf_dir).derive({"events": odd}, on="v").rewrite(SubstituteModality("v", "t"))
    with pytest.raises(ir.PlanError, match="empty key"):
        MediaFrame.of(spark.range(5)).fold([], lambda df, keys: df, max_group_rows=3).to_df()


def test_rewrites_keep_the_schema(spark, sf_dir):
    plans = [points.direct(spark, sf_dir), points.narration(spark, sf_dir), points.narrow(spark, sf_dir)]
    kinds = [{f.name: f.dataType.simpleString() for f in p.to_df().schema} for p in plans]
    assert kinds[0]["events"] == kinds[1]["events"] == kinds[2]["events"]
    assert set(kinds[0]) == set(kinds[1]) == set(kinds[2])


def test_span_rewrites_keep_the_schema(spark, sf_dir):
    folded = [MediaFrame(p(spark, sf_dir).node.child).to_df() for p in spans.PLANS.values()]
    kinds = [{f.name: f.dataType.simpleString() for f in df.schema} for df in folded]
    assert kinds[0] == kinds[1] == kinds[2]
    n = spans.sources(spark, sf_dir).count()
    assert all(df.count() == n for df in folded)


def test_narrow_spans_read_segments_of_windows_only(spark, sf_dir):
    """The footage is cut from the segment table; no plan of the clips scans whole texts beside it but the transcript's."""
    watched = spans.narrow(spark, sf_dir).stage("watched")
    told = watched._jdf.queryExecution().optimizedPlan().toString()
    assert "payload" in told and "contains" in told.lower()
    assert "substring(text" not in told


def test_both_rewrites_share_one_scan(spark, sf_dir):
    rows = spans.one_scan_plans(spark, sf_dir).collect()
    found = {(r.source_id, r.task_id): r for r in rows}
    narration = spans.span_narration(spark, sf_dir).groupBy("source_id", "task_id").count().collect()
    assert {(r.source_id, r.task_id): r["count"] for r in narration} == {k: r.n_said for k, r in found.items()}


def test_narration_never_reads_footage(spark, sf_dir):
    plan = spans.direct(spark, sf_dir).rewrite(SubstituteModality("v", "t")).to_df()
    assert "MapInPandas" not in plan._jdf.queryExecution().executedPlan().toString()


def test_plans_hold_no_nested_loops(spark, sf_dir):
    """Interval, point, band, word and pair joins are equi joins; scans push filters down and read only what is used."""
    from mediarel.workloads import algebra, crosscam

    physical = lambda df: df._jdf.queryExecution().executedPlan().toString()
    for query in (points.point_direct, points.point_narrow, spans.span_candidates, spans.span_windows, spans.span_narrow, crosscam.xcam_pairs, crosscam.pair_candidates, algebra.join_interval_dense, algebra.join_band, algebra.resolve_conflicts):
        told = physical(query(spark, sf_dir))
        assert "CartesianProduct" not in told and "BroadcastNestedLoopJoin" not in told, query.__name__
    told = physical(points.reference(spark, sf_dir))
    assert "EqualTo(event_type,purchase)" in told and "GreaterThanOrEqual(value" in told and "props" not in told


def test_whole_windows_equal_the_direct_plan(spark, sf_dir):
    """A clip that is the whole source gives what the direct plan gives."""
    everything = SemanticFn("all", "everything", "t", "array<struct<start_ms:bigint,end_ms:bigint,score:double>>", lambda df, on, into: df.withColumn(into, F.array(F.struct(F.lit(0).cast("bigint").alias("start_ms"), F.col("duration_ms").alias("end_ms"), F.lit(1.0).alias("score")))))
    wide = points.direct(spark, sf_dir).rewrite(PushdownWindows(everything, "t", 0, 0, reconcile.points(0)))
    told = lambda p: sorted(map(tuple, p.to_df().select("source_id", "events.start_ms").distinct().collect()))
    assert told(wide) == told(points.direct(spark, sf_dir))


def test_padding_is_monotone(spark, sf_dir):
    rows = sorted(map(tuple, points.pad_sweep(spark, sf_dir).select("pad_ms", "window_ms", "n_covered").collect()))
    assert all(a[1] <= b[1] and a[2] <= b[2] for a, b in zip(rows, rows[1:]))


def test_cheap_filters_move_below_semantic_maps(spark):
    fn = SemanticFn("f", "f", "x", "boolean", lambda df, on, into: df.withColumn(into, F.lit(True)))
    plan = MediaFrame.of(spark.range(3).withColumn("x", F.lit("a"))).derive({"flag": fn}, on="x").keep("id > 1").rewrite(OrderFilters())
    assert isinstance(plan.node, ir.Map) and isinstance(plan.node.child, ir.Filter)
    assert plan.to_df().count() == 1


def test_metered_calls_do_not_depend_on_partitions(spark, tmp_path):
    fn = SemanticFn("len", "length", "x", "bigint", lambda df, on, into: df)
    df = spark.range(50).select(F.concat(F.lit("text "), "id").alias("x"))
    totals = set()
    for parts in (1, 5):
        out = call_model(df.repartition(parts), fn, "x", "answer", lambda: lambda texts: [len(t) for t in texts], folder=str(tmp_path / str(parts)))
        totals.add(out.agg(F.sum("tokens"), F.sum("calls"), F.sum("answer")).first())
    assert len(totals) == 1


def test_an_answer_is_paid_once(spark, tmp_path):
    fn = SemanticFn("twice", "double it", "x", "string", lambda df, on, into: df)
    df = spark.createDataFrame([("a",), ("b",), ("a",)], "x string")
    first = call_model(df, fn, "x", "y", lambda: lambda texts: [t * 2 for t in texts], folder=str(tmp_path)).collect()
    assert sorted(r.y for r in first) == ["aa", "aa", "bb"]

    def refuses():
        def answer(texts):
            raise AssertionError(f"paid again for {texts}")

        return answer

    # A retry and a new plan over the same inputs find the stored answers; only a new input is asked.
    assert sorted(r.y for r in call_model(df, fn, "x", "y", refuses, folder=str(tmp_path)).collect()) == ["aa", "aa", "bb"]
    more = df.union(spark.createDataFrame([("c",)], "x string"))
    asked = call_model(more, fn, "x", "y", lambda: lambda texts: ["new"] * len(texts), folder=str(tmp_path)).collect()
    assert sorted(r.y for r in asked) == ["aa", "aa", "bb", "new"]


def test_ledger_and_stage_times(spark, sf_dir):
    plan = points.narrow(spark, sf_dir)
    done, ledger = plan.metered()
    paid = {r.fn: r for r in ledger.collect()}
    n = points.sources(spark, sf_dir).count()
    windows = points.point_windows(spark, sf_dir).agg(F.count("*"), F.sum(F.col("end_ms") - F.col("start_ms"))).first()
    assert paid["goal candidates"].calls == n and paid["goal candidates"].watched_ms == 0
    assert (paid["goals in footage"].calls, paid["goals in footage"].watched_ms) == tuple(windows)
    assert done.columns == plan.to_df().columns and sorted(map(str, done.collect())) == sorted(map(str, plan.to_df().collect()))
    timed, seconds = plan.timed()
    assert [s[0] for s in seconds] == [*reversed(plan.stages()), "result"] and all(s[1] >= 0 for s in seconds) and timed.count() == seconds[-1][2]


def test_stored_representations_are_made_once(spark, tmp_path):
    from mediarel.sources import stored

    spark.range(5).write.parquet(str(tmp_path / "in"))
    made = []

    def build():
        made.append(1)
        return spark.read.parquet(str(tmp_path / "in")).withColumn("twice", F.col("id") * 2)

    for _ in range(2):
        assert stored.representation(spark, "twice", "1", str(tmp_path / "in"), build, str(tmp_path)).count() == 5
    assert len(made) == 1
    stored.representation(spark, "twice", "2", str(tmp_path / "in"), build, str(tmp_path))
    spark.range(3).write.mode("append").parquet(str(tmp_path / "in"))
    assert stored.representation(spark, "twice", "2", str(tmp_path / "in"), build, str(tmp_path)).count() == 8
    assert len(made) == 3


def test_compose_runs_right_to_left():
    assert compose(lambda x: x + "b", lambda x: x + "a")("") == "ab"


def test_point_measures_move_as_expected(spark, sf_dir):
    curve = {(r.plan, r.threshold): r for r in points.m_point_curve(spark, sf_dir).collect()}
    assert curve["narrow", 30_000].f1 >= curve["direct", 30_000].f1
    assert curve["narration", 5_000].f1 < curve["narration", 30_000].f1
    assert curve["narrow", 5_000].f1 == curve["narrow", 60_000].f1


def test_iou_matrix_is_symmetric():
    a = np.array([[0, 0, 10, 10], [5, 5, 10, 10.0]])
    m = vision.iou_matrix(a, a)
    assert np.allclose(m, m.T) and np.allclose(np.diag(m), 1)


def test_catalog_is_consistent():
    assert set(catalog.oracle_sql()) <= set(catalog.queries())


def test_streams_equal_batches(spark, sf_dir, tmp_path):
    from mediarel.streaming import live

    events = spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    events.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = live.event_stream(spark, str(tmp_path / "in"), 10)
    got = live.run_available(live.candidate_windows(live.mentions(stream), lateness="60 days"), "live_windows", "complete")
    want = live.candidate_windows(live.mentions(spark.read.schema(live.EVENTS).parquet(str(tmp_path / "in"))))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    counts = live.run_available(live.mention_counts(live.event_stream(spark, str(tmp_path / "in"), 10), lateness="60 days"), "live_counts", "complete")
    assert counts.agg(F.sum("n")).first()[0] == events.count()
    doubled = live.event_stream(spark, str(tmp_path / "in"), 10)
    once = live.run_available(live.once(doubled.unionByName(doubled), lateness="60 days"), "live_once")
    assert once.count() == events.count()


def _events(spark, rows):
    return spark.createDataFrame(rows, "event_id bigint, ts string, user_id bigint, event_type string, value double, props string").withColumn("ts", F.col("ts").cast("timestamp"))


def _file(spark, folder, name, rows):
    """One file that the stream reads in its own batch, after those written before it."""
    import os
    import time

    part = folder / f"draft-{name}"
    _events(spark, rows).coalesce(1).write.parquet(str(part))
    (folder / "in").mkdir(exist_ok=True)
    made = next(part.glob("*.parquet"))
    os.rename(made, folder / "in" / f"{name}.parquet")
    when = time.time() - 1000 + 10 * len(list((folder / "in").iterdir()))
    os.utime(folder / "in" / f"{name}.parquet", (when, when))


def _row(i, clock, user=1, kind="purchase", value=200.0):
    return (i, f"2024-01-01 {clock}", user, kind, value, "{}")


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    from mediarel.streaming import live

    _file(spark, tmp_path, "a", [_row(1, "10:05:00"), _row(2, "10:10:00")])
    _file(spark, tmp_path, "b", [_row(3, "15:00:00")])
    # A row is late behind the watermark of the batch before its own.
    _file(spark, tmp_path, "b2", [_row(7, "15:05:00")])
    _file(spark, tmp_path, "c", [_row(4, "10:20:00"), _row(5, "15:10:00")])
    _file(spark, tmp_path, "d", [_row(6, "23:00:00")])
    counts, dropped = live.late_rows(live.mention_counts(live.event_stream(spark, str(tmp_path / "in"))), "live_late")
    assert dropped == 1
    assert sorted((str(r.start), r.n) for r in counts.collect()) == [("2024-01-01 10:00:00", 2), ("2024-01-01 15:00:00", 3)]
    sliding = live.run_available(live.mention_counts(live.event_stream(spark, str(tmp_path / "in")), "2 hours", "1 hour"), "live_sliding")
    assert {str(r.start)[11:13]: r.n for r in sliding.collect()}["09"] == 2


def test_stream_stream_join_equals_batch(spark, tmp_path):
    from mediarel.streaming import live

    rng = random.Random(5)
    rows = [_row(i, f"{10 + i // 40}:{rng.randrange(60):02d}:{rng.randrange(60):02d}", rng.randrange(3), rng.choice(["purchase", "error", "click"]), rng.choice([50.0, 200.0])) for i in range(160)]
    for k in range(0, 160, 40):
        _file(spark, tmp_path, f"{k:03d}", rows[k : k + 40])
    path = str(tmp_path / "in")
    streams = lambda: live.event_stream(spark, path)
    got = live.run_available(live.narrated_footage(live.mentions(streams()), streams().where("event_type = 'click'"), lateness="2 hours"), "live_joined")
    batch = spark.read.schema(live.EVENTS).parquet(path)
    want = live.narrated_footage(live.mentions(batch), batch.where("event_type = 'click'"))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) and want.count() > 10


def test_incremental_tracker_equals_batch(spark, tmp_path):
    import os
    import time

    from mediarel.streaming import live

    kind = "source_id bigint, ts timestamp, frame_no int, det_id bigint, cls string, colour string, subtype string, x double, y double, w double, h double, conf double, emb array<double>"
    dets = []
    for source in (1, 2):
        for k in range(3):
            for f in range(5 * k, 5 * k + 40):
                if (f * 3 + k) % 10:
                    dets.append((source, f * 1000, f, 1000 * k + f, "car", "red", "s", 8.0 * f * (k + 1), 100.0 * k, 50.0, 40.0, 0.9, [1.0]))
    far = [(source, 10_000_000 + 1000 * i, 10_000 + i, 1 + i, "car", "red", "s", 0.0, 0.0, 50.0, 40.0, 0.9, [1.0]) for i in range(2) for source in (1, 2)]
    # Rows arrive out of order within the allowed lateness; far frames move the watermark past all others.
    shuffled = sorted(dets, key=lambda d: (d[1] // 4000, random.Random(d[3]).random()))
    files = [shuffled[i : i + 60] for i in range(0, len(shuffled), 60)] + [far[:2], far[2:], [(9, 90_000_000, 90_000, 1, "car", "red", "s", 0.0, 0.0, 50.0, 40.0, 0.9, [1.0])], [(9, 99_000_000, 99_000, 1, "car", "red", "s", 0.0, 0.0, 50.0, 40.0, 0.9, [1.0])]]
    (tmp_path / "in").mkdir()
    for n, rows in enumerate(files):
        df = spark.createDataFrame([(r[0], r[1] / 1000, *r[2:]) for r in rows], kind.replace("ts timestamp", "ts double")).withColumn("ts", F.timestamp_seconds("ts"))
        df.coalesce(1).write.parquet(str(tmp_path / f"d{n}"))
        target = tmp_path / "in" / f"{n:03d}.parquet"
        os.rename(next((tmp_path / f"d{n}").glob("*.parquet")), target)
        os.utime(target, (time.time() - 1000 + n, time.time() - 1000 + n))
    stream = spark.readStream.schema(kind).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    got = {tuple(r) for r in live.run_available(live.track_detections(stream, lateness="10 seconds"), "live_tracks").collect()}
    want = set()
    for source in (1, 2):
        rows = [{"frame_no": d[2], "det_id": d[3], "cls": d[4], "colour": d[5], "subtype": d[6], "x": d[7], "y": d[8], "w": d[9], "h": d[10], "emb": d[12]} for d in dets if d[0] == source]
        want |= {(source, t["start_ms"], t["end_ms"], t["first_x"], t["first_y"], t["n_det"]) for t in vision.MotionTracker().tracks(rows)}
    assert want <= got and len(got - want) == 0 and want


def test_update_mode_and_restart_from_a_checkpoint(spark, tmp_path):
    from mediarel.streaming import live

    _file(spark, tmp_path, "a", [_row(1, "10:05:00"), _row(2, "11:10:00")])
    path, at, out = str(tmp_path / "in"), str(tmp_path / "state"), str(tmp_path / "out")
    live.write_each_batch(live.mentions(live.event_stream(spark, path)), out, at).awaitTermination()
    assert spark.read.parquet(out).count() == 2
    _file(spark, tmp_path, "b", [_row(3, "12:05:00"), _row(4, "12:15:00")])
    live.write_each_batch(live.mentions(live.event_stream(spark, path)), out, at).awaitTermination()
    assert sorted(r.event_id for r in spark.read.parquet(out).collect()) == [1, 2, 3, 4]
    assert {r.batch for r in spark.read.parquet(out).select("batch").distinct().collect()} == {0, 1}
    updated = live.run_available(live.mention_counts(live.event_stream(spark, path)), "live_updates", "update")
    latest = updated.groupBy("start").agg(F.max("n").alias("n"))
    assert sorted(r.n for r in latest.collect()) == [1, 1, 2]


def test_sketches_keep_their_bounds(spark):
    rng = random.Random(2)
    rows = [(g, rng.randrange(4000), rng.random() * 1000) for g in range(3) for _ in range(20_000)]
    df = spark.createDataFrame(rows, "g int, v int, x double")
    error = F.approx_count_distinct("v", 0.02).alias("near"), F.countDistinct("v").alias("exact")
    for r in df.groupBy("g").agg(*error).collect():
        # Three standard errors of the sketch.
        assert abs(r.near - r.exact) <= 3 * 0.02 * r.exact
    for r in df.groupBy("g").agg(F.percentile_approx("x", 0.5, 10_000).alias("m"), F.collect_list("x").alias("all")).collect():
        # The rank is off by n / accuracy at most.
        at = sum(x <= r.m for x in r.all) / len(r.all)
        assert abs(at - 0.5) <= 1 / 10_000 + 1 / len(r.all)


def test_text_binary_and_bucketed_sources(spark, tmp_path):
    from mediarel.sources import scan

    (tmp_path / "files").mkdir()
    for i in range(3):
        (tmp_path / "files" / f"{i}.txt").write_text(f"line {i}\nmore")
    assert scan.scan(spark, str(tmp_path / "files"), "text").count() == 6
    seen = scan.scan(spark, str(tmp_path / "files"), "binaryFile").select(F.length("content").alias("n")).collect()
    assert [r.n for r in seen] == [11, 11, 11]
    spark.sql(f"CREATE DATABASE IF NOT EXISTS bucketed LOCATION '{tmp_path}/db'")
    df = spark.range(100).select(F.col("id").alias("source_id"), (F.col("id") % 7).alias("x"))
    for name in ("bucketed.a", "bucketed.b"):
        scan.write_bucketed(df, name, 4)
    joined = scan.scan(spark, "bucketed.a", "table").hint("merge").join(scan.scan(spark, "bucketed.b", "table").withColumnRenamed("x", "y"), "source_id")
    assert joined.count() == 100 and "Exchange" not in joined._jdf.queryExecution().sparkPlan().toString()
    spark.sql("DROP DATABASE bucketed CASCADE")


def test_manifests_and_sinks(spark, tmp_path):
    from mediarel.sources import scan

    scan.register(spark)
    df = spark.read.format("media_manifest").option("sources", 10).option("parts", 3).load()
    assert df.count() == 10
    df.write.json(str(tmp_path / "m"))
    assert scan.scan_manifest(spark, str(tmp_path / "m")).select("v.uri").count() == 10
    scan.write_clustered(df.withColumn("segment_no", F.lit(0)), str(tmp_path / "seg"), 4)
    assert spark.read.parquet(str(tmp_path / "seg")).count() == 10
    for fmt in ("csv", "orc"):
        df.write.format(fmt).save(str(tmp_path / fmt))
        assert scan.scan(spark, str(tmp_path / fmt), fmt, "source_id bigint, uri string, duration_ms bigint").count() == 10
    shutil.rmtree(tmp_path / "m")


def test_table_scale_join_is_settled_one_to_one(spark, tmp_path):
    import datetime as dt
    import random

    from mediarel.workloads import algebra

    rng, start = random.Random(7), dt.datetime(2020, 1, 1)
    n_supp, n_part = 6, 40
    lines = [(rng.randrange(n_supp), rng.randrange(n_part), start + dt.timedelta(days=rng.randrange(40))) for _ in range(700)]
    spark.createDataFrame(lines, "l_suppkey long, l_partkey long, l_shipdate timestamp").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame([(i, i % 2) for i in range(n_supp)], "s_suppkey long, s_nationkey long").write.parquet(f"{tmp_path}/supplier.parquet")
    spark.createDataFrame([(i, f"b{i % 2}", f"t{i % 3}") for i in range(n_part)], "p_partkey long, p_brand string, p_type string").write.parquet(f"{tmp_path}/part.parquet")
    held = {}
    for s, p, d in lines:
        day = (d - dt.datetime(1970, 1, 1)).days
        b, e = held.get((s, p), (day, day + 1))
        held[s, p] = min(b, day), max(e, day + 1)
    scored = []
    for (s, p), (b, e) in held.items():
        for (t, q), (c, f) in held.items():
            both = min(e, f) - max(b, c)
            if s < t and s % 2 == t % 2 and p % 6 == q % 6 and both > 0:
                scored.append((s, t, -round(both / (e - b + f - c - both), 6), p, q))
    used, want = set(), set()
    for s, t, score, p, q in sorted(scored):
        if not {(s, t, "l", p), (s, t, "r", q)} & used:
            used |= {(s, t, "l", p), (s, t, "r", q)}
            want.add((s, t, p, q, -score))
    got = [tuple(r) for r in algebra.xcam_tables_settled(spark, str(tmp_path)).collect()]
    assert len(got) == len(set(got)) and set(got) == want and len(want) < len(scored)


@pytest.mark.parametrize("parts", [1, 5])
def test_equal_extremes_name_the_first_event(spark, tmp_path, parts):
    rows = [(i, "a", (5.0, 0.0, 2.0)[i % 3]) for i in range(30)] + [(40, "a", None), (41, "b", None), (42, "c", -1.0), (43, "c", None), (None, "c", 9.0)]
    spark.createDataFrame(rows, "event_id bigint, event_type string, value double").repartition(parts).sortWithinPartitions(F.desc("event_id")).write.parquet(f"{tmp_path}/events.parquet")
    told = {r.event_type: (r.high, r.top_id, r.low_id) for r in relational.QUERIES["agg_conditional"](spark, str(tmp_path)).collect()}
    assert told == {"a": (0, 0, 1), "b": (0, None, None), "c": (0, 42, 42)}


def test_a_stretch_shows_a_passage_in_each_of_its_documents(spark, tmp_path):
    passage, filler = "violet lanterns drifted slowly across harbour", "a b c " * 400
    texts = [f"one\n{passage}\nend", f"two\n{passage}\nend", f"{passage}\n{filler}\n{passage}"]
    rows = [(i, text, "en", "web", len(text)) for i, text in enumerate(texts)] + [(3, passage, "en", "alone", len(passage)), (4, None, "en", "web", 0)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(7, passage), (8, passage)], "item_id bigint, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    told = {r.plan: r for r in spans.two_in_one_plans(spark, str(tmp_path)).collect()}
    assert (told["narrow"].n_pred, told["narrow"].n_ref, told["narrow"].tp, told["narrow"].f1) == (3, 3, 3, 1.0)
    assert (told["narration"].n_pred, told["narration"].n_over_wide) == (2, 1)
    # A later place in a stretch of its own is no event, nor is a place that a stretch cuts.
    placed = docs.where("doc_id = 2").selectExpr("doc_id AS source_id", "source", "text", "10L AS at")
    asked = spans.tasks(spark, str(tmp_path))
    events = lambda a, b: [(r.start_ms, r.end_ms) for r in spans.watched_in(spark.createDataFrame([("web", a, b)], "source string, start_ms bigint, end_ms bigint"), placed, asked).collect()]
    assert events(0, 10_000) == [(500, 500 + 50 * len(passage))]
    assert events(550, 10_000) == events(20_000, 1_000_000) == []
