"""Mixing sources to target weights by entropy balancing.

Rates of documents stay as near as they can, in relative entropy per document, to taking every document once, while the words
of every source meet a target and no rate exceeds ``most``. The dual has one multiplier a source, and a
document's rate is tilted exponentially by its words: ``min(most, exp(lambda * size))``. So a source that is short of words
repeats its long documents first, and one that has too many leaves them out first.

The dual needs only how many documents of each size a source has. One aggregation of the documents leaves those cells; Newton steps
run on them for all sources at once, one task a source, and never see documents. Rates become copies cell by cell: systematic
rounding in order of size, then a repair with smaller and smaller documents, so a source misses its target by less than its
smallest document that still has room.

Defined cases: null text has size 0; null source is a source of its own, last in order; documents
of size 0 take 0 words; a very long text is one document like others, left out where it alone exceeds the target;
documents of equal source and size (ties) get copies in order of doc_id modulo ``DEALS`` and doc_id, null first; an empty table gives an
empty result; repeated rows are separate rows; other columns pass through, and columns named as in ``ADDED`` are replaced.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from mediarel.llm import common

#: Rates are rounded to this many parts before they become copies: integer steps are exact.
RATE_PARTS = 1_000_000
ADDED = ("size", "source_size", "target", "rate", "copies", "taken")
#: Rows of one (source, size) are dealt into so many parts before they are numbered.
DEALS = 64


def _numbered(sizes: DataFrame) -> DataFrame:
    """``sizes`` with ``place``: the number of each source in code-point order, null last, by a distributed sort."""
    ordered = sizes.orderBy("missing", "name").withColumns({"part": F.spark_partition_id(), "row": F.monotonically_increasing_id()})
    ordered = common.materialise(ordered, "mix-sources")
    # One row for each partition of the sort.
    held = ordered.groupBy("part").agg(F.count("*").alias("held"), F.min("row").alias("first"))
    before = F.coalesce(F.sum("held").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return ordered.join(F.broadcast(held.select("part", "first", before.alias("before"))), "part").withColumn("place", F.col("before") + F.col("row") - F.col("first")).drop("part", "row", "first", "before")


def source_targets(sizes: DataFrame, weights: Sequence[float], share: float, most: float) -> DataFrame:
    """Targets from (missing, name, source_size): a share of all words, split by weights that repeat over the
    sources in code-point order (null last), none above ``most`` times its source.

    The excess is reshared by weight until none is above: sources that are full leave, and the others share the rest.
    """
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.col("place") % len(weights) + 1).cast("int"))
    placed = common.materialise(_numbered(sizes).withColumn("weight", weight).withColumn("cap", F.lit(float(most)) * F.col("source_size")), "mix-weights")
    level, full = 0.0, -1
    while True:
        over = F.col("cap") <= F.col("weight") * F.lit(level) if full >= 0 else F.lit(False)
        row = placed.agg(F.sum("source_size").alias("all"), F.count_if(over).alias("full"), F.sum(F.when(over, F.col("cap"))).alias("held"), F.sum(F.when(~over, F.col("weight"))).alias("open")).first()
        if row["full"] == full:
            break
        full = row["full"]
        level = (share * (row["all"] or 0) - (row["held"] or 0.0)) / row["open"] if row["open"] else float("inf")
    return placed.select("missing", "name", "source_size", F.round(F.least(F.col("cap"), F.col("weight") * F.lit(level)), 6).alias("target"))


def balance(size: np.ndarray, n: np.ndarray, target: float, most: float, tolerance: float = 1e-13, steps: int = 200) -> float:
    """The multiplier of a source: Newton steps on its dual, held in a bracket.

    ``n`` documents have ``size`` words each. Words taken, ``sum(n * size * min(most, exp(lambda * size)))``, rise with the multiplier.
    """
    words = (n * size).astype(float)
    if target >= most * words.sum():
        return float(np.log(most) / size.min())

    def taken(at: float) -> tuple[float, float]:
        rate = np.exp(np.minimum(at * size, np.log(most)))
        return float((words * rate).sum()) - target, float((words * size * rate)[at * size < np.log(most)].sum())

    low, high = (0.0, float(np.log(most) / size.min())) if target > words.sum() else (-1.0 / float(size.max()), 0.0)
    while low < 0 and taken(low)[0] > 0:
        low, high = 2 * low, low
    at = high if low < 0 else low
    for _ in range(steps):
        miss, slope = taken(at)
        if abs(miss) <= tolerance * target:
            break
        low, high = (at, high) if miss < 0 else (low, at)
        step = at - miss / slope if slope > 0 else low
        at = step if low < step < high else (low + high) / 2
        if not low < at < high:
            break
    return at


def settle(size: np.ndarray, n: np.ndarray, parts: np.ndarray, target: float, most: int) -> np.ndarray:
    """Copies of all documents of each size, sizes descending: systematic rounding, then what is missing or too much, largest first."""
    ends = np.cumsum(n * parts)
    steps = (ends + RATE_PARTS // 2) // RATE_PARTS
    copies = np.diff(steps, prepend=0)
    miss = int(np.floor(target + 0.5)) - int((copies * size).sum())
    for k in range(len(size)):
        if not miss:
            break
        d = abs(miss) // int(size[k]) * (1 if miss > 0 else -1)
        d = min(max(d, -int(copies[k])), most * int(n[k]) - int(copies[k]))
        copies[k] += d
        miss -= d * int(size[k])
    return copies


def _settled(cells: DataFrame, most: int) -> DataFrame:
    """missing, name, size, parts, held (copies of all its documents) for cells (missing, name, size, n, target) of sizes above 0."""

    def one(cell: pd.DataFrame) -> pd.DataFrame:
        cell = cell.sort_values("size", ascending=False)
        size, n, target = cell["size"].to_numpy(np.int64), cell["n"].to_numpy(np.int64), float(cell["target"].iloc[0])
        parts = np.zeros(len(size), np.int64)
        if target > 0:
            rate = np.exp(np.minimum(balance(size, n, target, most) * size, np.log(most)))
            parts = np.minimum(most * RATE_PARTS, np.floor(rate * RATE_PARTS + 0.5).astype(np.int64))
        return pd.DataFrame({"missing": cell["missing"], "name": cell["name"], "size": size, "parts": parts, "held": settle(size, n, parts, target, most)})

    # A group has a row for each distinct size of a source, however many documents it has.
    return cells.groupBy("missing", "name").applyInPandas(one, "missing boolean, name string, size long, parts long, held long")


def mix(docs: DataFrame, weights: Sequence[float] = (3, 1, 2), share: float = 1.5, most: int = 2, size: Column | None = None, tie: Column | None = None) -> DataFrame:
    """Adds ``size, source_size, target, rate, copies, taken`` to documents (doc_id, source, and text or ``size``).

    ``size`` defaults to the words of ``text``, and ``tie``, which orders rows that share a doc_id, to its hash. No document is taken more than ``most`` times, a whole number.
    """
    kept = [c for c in docs.columns if c not in ADDED]
    own = "_mix"
    while any(c.lower().startswith(own) for c in docs.columns):
        own += "_"
    words = F.coalesce(common.n_words(F.col("text")) if size is None else size.cast("long"), F.lit(0).cast("long"))
    cell = F.struct(F.col("source").isNull().alias("missing"), F.coalesce(F.col("source").cast("string"), F.lit("")).alias("name"), words.alias("size"), F.coalesce(F.pmod("doc_id", F.lit(DEALS)), F.lit(-1)).cast("int").alias("deal"))
    sized = docs.withColumn(own, cell)
    deals = common.materialise(sized.select(f"{own}.*").groupBy("missing", "name", "size", "deal").agg(F.count("*").alias("n")), "mix-counts")
    sizes = deals.groupBy("missing", "name").agg(F.sum(F.col("size") * F.col("n")).alias("source_size"))
    targets = common.materialise(source_targets(sizes, weights, share, most), "mix-targets")
    cells = deals.where("size > 0").groupBy("missing", "name", "size").agg(F.sum("n").alias("n")).join(targets.select("missing", "name", "target"), ["missing", "name"])
    settled = common.materialise(_settled(cells, most), "mix-copies")

    # Copies that a deal gets: the whole ones of its documents, and those of the rest that earlier deals leave.
    by_deal = Window.partitionBy("missing", "name", "size").orderBy("deal")
    whole = Window.partitionBy("missing", "name", "size")
    dealt = (
        deals.withColumns({"earlier": F.sum("n").over(by_deal) - F.col("n"), "all": F.sum("n").over(whole)})
        .join(settled, ["missing", "name", "size"], "left")
        .join(targets, ["missing", "name"])
        .select(
            F.struct("missing", "name", "size", "deal").alias(own),
            F.struct(
                "source_size",
                "target",
                F.coalesce(F.col("parts") / RATE_PARTS, F.lit(0.0)).alias("rate"),
                F.coalesce(F.expr("held div all"), F.lit(0)).cast("long").alias("each"),
                (F.coalesce(F.expr("held % all"), F.lit(0)) - F.col("earlier")).alias("more"),
            ).alias(f"{own}_dealt"),
        )
    )
    # Rows that share a doc_id are ordered by their text, so that reruns agree.
    if tie is None and "text" in docs.columns:
        tie = F.xxhash64("text")
    order = ["doc_id"] if tie is None else ["doc_id", tie]
    place = F.row_number().over(Window.partitionBy(own).orderBy(*order))
    met = sized.withColumn(f"{own}_place", place).join(dealt, own)
    n_copies = (F.col(f"{own}_dealt.each") + F.when(F.col(f"{own}_place") <= F.col(f"{own}_dealt.more"), 1).otherwise(0)).cast("long")
    made = [F.col(f"{own}.size").alias("size"), *[F.col(f"{own}_dealt.{c}").alias(c) for c in ("source_size", "target", "rate")], n_copies.alias("copies"), (n_copies * F.col(f"{own}.size")).cast("long").alias("taken")]
    return met.select(*[F.col(f"`{c}`") for c in kept], *made)


def repeat_copies(mixed: DataFrame, columns: Sequence[str]) -> DataFrame:
    """One row for each copy taken; documents without words are kept once, they cost nothing."""
    times = F.when(F.col("size") > 0, F.col("copies")).otherwise(1).cast("int")
    kept = mixed.select(*[F.col(f"`{c}`") for c in columns], times.alias("_times_"))
    return kept.where("_times_ > 0").withColumn("_times_", F.explode(F.array_repeat(F.lit(0), F.col("_times_")))).select(*[F.col(f"`{c}`") for c in columns])


def op10_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    sized = docs.select("doc_id", "source", common.n_words(F.col("text")).alias("words"))
    return mix(sized, size=F.col("words")).select("doc_id", "size", "source_size", "target", "taken")


#: The same dual by bisection, and the repair as a walk over sizes.
OP10_SQL = """
WITH RECURSIVE d AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')) AS BIGINT) AS size,
         coalesce(((doc_id % 64) + 64) % 64, -1) AS deal
  FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
w AS (
  SELECT source, source_size, 2.0 * source_size AS cap,
         CAST(CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 3 WHEN 1 THEN 1 ELSE 2 END AS DOUBLE) AS weight,
         row_number() OVER (ORDER BY source NULLS LAST) AS place
  FROM s),
f AS (
  SELECT *, cap / weight AS fills_at,
         (1.5 * sum(source_size) OVER () - coalesce(sum(cap) OVER (ORDER BY cap / weight, place ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
         / sum(weight) OVER (ORDER BY cap / weight, place ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level
  FROM w),
t AS (
  SELECT place, source, source_size, round(CAST(least(cap, weight * (SELECT level FROM f WHERE level <= fills_at ORDER BY fills_at, place LIMIT 1)) AS DOUBLE), 6) AS target FROM f),
c AS (
  SELECT t.place, t.target, t.source_size, d.size, count(*) AS n, row_number() OVER (PARTITION BY t.place ORDER BY d.size DESC) AS k
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source WHERE d.size > 0 AND t.target > 0 GROUP BY t.place, t.target, t.source_size, d.size),
b AS (
  SELECT place, 0 AS step, CAST(-50 AS DOUBLE) AS lo, ln(2) / min(size) AS hi FROM c GROUP BY place
  UNION ALL
  SELECT b.place, any_value(b.step) + 1,
         CASE WHEN sum(n * size * exp(least((lo + hi) / 2 * size, ln(2)))) < any_value(target) THEN any_value((lo + hi) / 2) ELSE any_value(lo) END,
         CASE WHEN sum(n * size * exp(least((lo + hi) / 2 * size, ln(2)))) < any_value(target) THEN any_value(hi) ELSE any_value((lo + hi) / 2) END
  FROM b JOIN c ON c.place = b.place WHERE b.step < 110 GROUP BY b.place),
p AS (
  SELECT c.place, c.k, c.size, c.n, CAST(floor(c.target + 0.5) AS BIGINT) AS goal,
         CASE WHEN c.target >= 2 * c.source_size THEN 2000000 ELSE least(2000000, CAST(floor(exp(least(b.hi * c.size, ln(2))) * 1000000 + 0.5) AS BIGINT)) END AS parts
  FROM c JOIN b ON b.place = c.place AND b.step = 110),
e AS (SELECT *, CAST(sum(n * parts) OVER (PARTITION BY place ORDER BY k) AS BIGINT) AS upto FROM p),
r AS (SELECT place, k, size, n, goal, (upto + 500000) // 1000000 - (upto - n * parts + 500000) // 1000000 AS held FROM e),
m AS (SELECT place, any_value(goal) - CAST(sum(held * size) AS BIGINT) AS miss FROM r GROUP BY place),
walk AS (
  SELECT place, CAST(0 AS BIGINT) AS k, CAST(0 AS BIGINT) AS size, CAST(0 AS BIGINT) AS n, CAST(0 AS BIGINT) AS copies, CAST(miss AS BIGINT) AS miss FROM m
  UNION ALL
  SELECT place, k, size, n, held + d, miss - d * size FROM (
    SELECT r.place, CAST(r.k AS BIGINT) AS k, r.size, CAST(r.n AS BIGINT) AS n, CAST(r.held AS BIGINT) AS held, walk.miss,
           CAST(least(greatest(CASE WHEN walk.miss > 0 THEN walk.miss // r.size ELSE -((-walk.miss) // r.size) END, -r.held), 2 * r.n - r.held) AS BIGINT) AS d
    FROM walk JOIN r ON r.place = walk.place AND r.k = walk.k + 1)),
o AS (
  SELECT d.doc_id, d.size, t.source_size, t.target, t.place AS at, row_number() OVER (PARTITION BY d.source, d.size ORDER BY d.deal, d.doc_id NULLS FIRST) AS place
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source)
SELECT o.doc_id, o.size, CAST(o.source_size AS BIGINT) AS source_size, o.target,
       CAST(CASE WHEN o.size > 0 THEN o.size * coalesce(walk.copies // walk.n + CASE WHEN o.place <= walk.copies % walk.n THEN 1 ELSE 0 END, 0) ELSE 0 END AS BIGINT) AS taken
FROM o LEFT JOIN walk ON walk.place = o.at AND walk.size = o.size AND walk.k > 0
"""
