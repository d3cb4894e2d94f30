"""Cutting, transcribing and sampling footage that is text: 50 ms a character."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from mediarel.operators import intervals

CHAR_MS = 50
SEGMENT_MS = 10_000
#: Characters of passages that one automaton may hold; more are searched in several passes.
AUTOMATON_CHARS = 32_000_000


def segments(df: DataFrame, segment_ms: int = SEGMENT_MS) -> DataFrame:
    """(source_id, segment_no, seg_start_ms, seg_end_ms, payload) slices of (source_id, text)."""
    width = segment_ms // CHAR_MS
    last = F.expr(f"(length(text) - 1) div {width}")
    dealt = df.where(F.length("text") > 0).select("source_id", "text", F.explode(F.sequence(F.lit(0).cast("bigint"), last)).alias("segment_no"))
    start = F.col("segment_no") * segment_ms
    return dealt.select(
        "source_id", "segment_no", start.alias("seg_start_ms"), F.least(start + segment_ms, F.length("text") * CHAR_MS).cast("bigint").alias("seg_end_ms"),
        F.expr(f"substring(text, int(segment_no * {width} + 1), {width})").alias("payload"),
    )


def view_segments(windows: DataFrame, table: DataFrame, keys: list[str], into: str = "clip", segment_ms: int = SEGMENT_MS) -> DataFrame:
    """Materialise windows (keys with source_id, start_ms, end_ms): interval join to the segment table, pieces trimmed and put in order.

    Only segments of windows are read beyond the join: a small window table is broadcast by Spark, a large one meets segments on (source_id, bucket).
    """
    joined = intervals.overlap_join(windows, table, ["source_id"], segment_ms * 4, right_span=("seg_start_ms", "seg_end_ms"))
    low = F.greatest(F.col("start_ms") - F.col("seg_start_ms"), F.lit(0))
    high = F.least(F.col("end_ms"), F.col("seg_end_ms")) - F.col("seg_start_ms")
    piece = joined.select(*keys, "start_ms", "end_ms", "segment_no", F.substring("payload", (low / CHAR_MS).cast("int") + 1, ((high - low) / CHAR_MS).cast("int")).alias("p"))
    ordered = F.array_sort(F.collect_list(F.struct("segment_no", "p")))
    return piece.groupBy(*keys, "start_ms", "end_ms").agg(F.concat_ws("", F.transform(ordered, lambda x: x["p"])).alias(into))


def transcribe_lines(df: DataFrame) -> DataFrame:
    """(source_id, line_no, start_ms, end_ms, line) of (source_id, text): lines on the source's clock."""
    each = df.select("source_id", F.posexplode(F.split("text", "\n")).alias("line_no", "line"))
    order = Window.partitionBy("source_id").orderBy("line_no").rowsBetween(Window.unboundedPreceding, -1)
    at = F.coalesce(F.sum(F.length("line") + 1).over(order), F.lit(0)).cast("bigint")
    placed = each.withColumn("start_ms", at * CHAR_MS)
    return placed.select("source_id", F.col("line_no").cast("bigint").alias("line_no"), "start_ms", (F.col("start_ms") + F.length("line") * CHAR_MS).cast("bigint").alias("end_ms"), "line")


def long_words(text: Column) -> Column:
    """Distinct lower-case runs of six letters or more."""
    return F.array_distinct(F.regexp_extract_all(F.lower(text), F.lit("[a-z]{6,}"), F.lit(0)))


def sample_fps(frames: DataFrame, per_second: int = 1, at: str = "ts_ms") -> DataFrame:
    """The first frame of every interval of a source: fewer frames cost fewer tokens."""
    slot = F.expr(f"`{at}` div {1000 // per_second}")
    place = F.row_number().over(Window.partitionBy("source_id", slot).orderBy(at, *[c for c in ("event_id", "frame_no") if c in frames.columns]))
    return frames.withColumn("_place", place).where("_place = 1").drop("_place")


def find_passages(df: DataFrame, passages: DataFrame, text: str = "text") -> DataFrame:
    """(source_id, task_id, offset, size): first place of every passage in every text.

    One pass of an Aho-Corasick automaton over each text finds all passages at once. Its size is checked; a larger passage table is
    searched in groups, each over all texts.
    """
    rows = [(r["task_id"], r["passage"]) for r in passages.where(F.length("passage") > 0).select("task_id", "passage").toLocalIterator()]
    groups: list[list] = [[]]
    held = 0
    for r in rows:
        if held + len(r[1]) > AUTOMATON_CHARS and groups[-1]:
            groups.append([])
            held = 0
        groups[-1].append(r)
        held += len(r[1])
    found = None
    for group in groups:
        sent = df.sparkSession.sparkContext.broadcast(group)

        def search(batches: Iterator[pd.DataFrame], sent=sent) -> Iterator[pd.DataFrame]:
            import ahocorasick

            machine = ahocorasick.Automaton()
            ids: dict[str, list] = {}
            for task, passage in sent.value:
                ids.setdefault(passage, []).append(task)
                machine.add_word(passage, passage)
            if len(ids):
                machine.make_automaton()
            for batch in batches:
                out = []
                for source, body in zip(batch["source_id"], batch["text"], strict=True):
                    seen = set()
                    for end, passage in machine.iter(body) if len(ids) and isinstance(body, str) else ():
                        if passage not in seen:
                            seen.add(passage)
                            out += [(source, task, end - len(passage) + 1, len(passage)) for task in ids[passage]]
                yield pd.DataFrame(out, columns=["source_id", "task_id", "offset", "size"])

        part = df.select("source_id", F.col(text).alias("text")).mapInPandas(search, "source_id long, task_id long, offset long, size long")
        found = part if found is None else found.unionByName(part)
    return found
