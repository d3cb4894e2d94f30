"""Quality rules: a learned decision list over text statistics, native Spark only.

Statistics of a text come from array and string functions inside one row, so long texts cost
n log n and no shuffle. Sequential covering grows a conjunction of thresholds that separates bad
labelled rows from good ones on a growing part, prunes it on a held-out part, keeps it if it is
precise enough there, removes what it covers and goes on. The list becomes one ordered ``CASE`` expression.

Fitting uses at most ``FIT_ROWS`` labelled rows of either class, those with the smallest hash of
their id: a documented bound; a document that is labelled both ways counts as bad. Statistics, rules and verdicts cover every row.

Defined cases: null and blank texts have zero words and fail the base rule; repeated rows are judged
alike; without labelled rows of both classes the list is empty and the base rule alone decides;
an empty table gives an empty result; equal gains of two tests (ties) go to the first in order of statistic and threshold;
other columns pass through, and columns of the result's names are replaced.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Callable, Mapping, Sequence
from dataclasses import dataclass
from functools import reduce
from operator import and_

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from mediarel.llm import common

#: Labelled rows of either class that a list is fitted on at most.
FIT_ROWS = 3000
#: Thresholds tried for each statistic: its quantiles among the rows to fit on.
CUTS = 24
SYMBOLS = "#*$%&|<>"
WINDOW = 5

STATS = ("n_words", "mean_word", "symbol_share", "dup_line_share", "repeat_share", "capital_share", "bang_share", "distinct_share")


@dataclass(frozen=True)
class Test:
    """One threshold on one statistic."""

    stat: str
    above: bool
    cut: float

    def holds(self, row: Mapping[str, float]) -> bool:
        return row[self.stat] > self.cut if self.above else row[self.stat] <= self.cut

    def column(self) -> Column:
        return F.col(self.stat) > F.lit(self.cut) if self.above else F.col(self.stat) <= F.lit(self.cut)

    def __str__(self) -> str:
        return f"{self.stat} {'>' if self.above else '<='} {self.cut:g}"


Rule = tuple[Test, ...]


def _let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once, however often the body names it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _covered(starts: Column) -> Column:
    """Positions that windows with these ascending starts cover."""
    first = F.struct(F.lit(-WINDOW).alias("last"), F.lit(0).cast("long").alias("total"))
    return F.aggregate(
        starts,
        first,
        lambda s, x: F.struct(x.alias("last"), (s["total"] + F.least(F.lit(WINDOW), x - s["last"])).alias("total")),
        lambda s: s["total"],
    )


def _repeat_words(words: Column) -> Column:
    """Words in windows that occur twice or more. Only texts with an equal pair of windows sort them."""

    def twins(windows: Column) -> Column:
        near = lambda p, i: F.coalesce(F.get(windows, i)["h"] == p["h"], F.lit(False))
        return F.array_sort(F.transform(F.filter(windows, lambda p, i: near(p, i - 1) | near(p, i + 1)), lambda p: p["i"]))

    def marked(hashes: Column) -> Column:
        windows = F.array_sort(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        return F.when(F.size(F.array_distinct(hashes)) < F.size(hashes), _covered(_let(windows, twins))).otherwise(F.lit(0).cast("long"))

    window = lambda i: F.xxhash64(*[F.get(words, i + k) for k in range(WINDOW)])
    some = F.size(words) > WINDOW
    return F.when(some, _let(F.transform(F.sequence(F.lit(0), F.size(words) - WINDOW), window), marked)).otherwise(F.lit(0).cast("long"))


def with_statistics(docs: DataFrame) -> DataFrame:
    """Adds the counts of the base rule and the shares that rules test, all never null."""
    text = common.empty_if_null(F.col("text"))
    words = F.split(F.btrim(text, F.lit(common.WORD_SEPARATORS)), common.SEPARATOR_PATTERN)
    gone = lambda drop: (F.length(text) - F.length(F.translate(text, drop, ""))).cast("long")
    lines = F.filter(F.split(text, "\n"), lambda line: line.rlike(common.WORD_PATTERN))
    of_words = _let(
        words,
        lambda w: F.struct(
            F.when(F.get(w, F.lit(0)) == "", 0).otherwise(F.size(w)).cast("long").alias("n_words"),
            F.size(F.array_distinct(w)).cast("long").alias("n_distinct"),
            _repeat_words(w).alias("n_repeat_words"),
        ),
    )
    of_lines = _let(lines, lambda x: F.struct(F.size(x).cast("long").alias("n_lines"), (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines")))
    counted = docs.withColumns(
        {
            "_w": of_words,
            "_l": of_lines,
            "word_chars": (F.length(text) - gone(common.WORD_SEPARATORS)).cast("long"),
            "n_symbols": gone(SYMBOLS),
            "_capitals": gone("ABCDEFGHIJKLMNOPQRSTUVWXYZ"),
            "_bangs": gone("!"),
        }
    )
    counted = counted.withColumns({"n_words": F.col("_w.n_words"), "n_repeat_words": F.col("_w.n_repeat_words"), "n_dup_lines": F.col("_l.n_dup_lines")})
    share = lambda part, whole: F.when(whole > 0, part / whole).otherwise(F.lit(0.0))
    n, chars = F.col("n_words"), F.col("word_chars")
    return counted.withColumns(
        {
            "mean_word": share(chars, n),
            "symbol_share": share(F.col("n_symbols"), chars),
            "dup_line_share": share(F.col("n_dup_lines"), F.col("_l.n_lines")),
            "repeat_share": share(F.col("n_repeat_words"), n),
            "capital_share": share(F.col("_capitals"), chars),
            "bang_share": share(F.col("_bangs"), chars),
            "distinct_share": share(F.col("_w.n_distinct"), n),
            "base_failed": (n < 10) | (100 * F.col("n_repeat_words") > 20 * n),
        }
    ).drop("_w", "_l", "_capitals", "_bangs")


def _bits(rows: Sequence[Mapping], holds: Callable[[Mapping], bool]) -> int:
    return int("".join("1" if holds(r) else "0" for r in reversed(rows)) or "0", 2)


def _cuts(values: Sequence[float]) -> list[float]:
    """Midpoints at the quantiles of the distinct values."""
    found = sorted(set(values))
    spots = sorted({i * (len(found) - 1) // CUTS for i in range(1, CUTS)} - {len(found) - 1}) if len(found) > 1 else []
    return [(found[i] + found[i + 1]) / 2 for i in spots]


def learn_rules(rows: Sequence[Mapping], precision: float = 0.97, least: int = 5, most_tests: int = 3, most_rules: int = 12, stats: Sequence[str] = STATS) -> list[Rule]:
    """Ordered conjunctions that mark bad rows (``bad`` true), by sequential covering.

    Every third row is held out for pruning. A rule grows by the test with the largest information
    gain, loses the tests that the held-out rows do not need, and must reach ``precision`` there and on the growing rows.
    """
    if not any(r["bad"] for r in rows) or all(r["bad"] for r in rows):
        return []
    bad, everything = _bits(rows, lambda r: r["bad"]), (1 << len(rows)) - 1
    prune = int("".join("1" if i % 3 == 2 else "0" for i in reversed(range(len(rows)))), 2)
    bad_values = [r for r in rows if r["bad"]]
    tests = {}
    for stat in stats:
        for cut in sorted({*_cuts([r[stat] for r in rows]), *_cuts([r[stat] for r in bad_values])}):
            over = _bits(rows, Test(stat, True, cut).holds)
            tests[Test(stat, True, cut)] = over
            tests[Test(stat, False, cut)] = everything & ~over

    def counts(mask: int) -> tuple[int, int]:
        return (mask & bad).bit_count(), (mask & ~bad).bit_count()

    rules: list[Rule] = []
    left = everything
    while len(rules) < most_rules:
        rule: list[Test] = []
        inside = left & ~prune
        p, n = counts(inside)
        while p and n and len(rule) < most_tests:

            def gain(mask: int, p: int = p, n: int = n, inside: int = inside) -> float:
                q, m = counts(inside & mask)
                return q * (math.log2(q / (q + m)) - math.log2(p / (p + n))) if q else 0.0

            best = max(tests, key=lambda t: gain(tests[t]))
            if gain(tests[best]) <= 1e-9:
                break
            rule.append(best)
            inside &= tests[best]
            p, n = counts(inside)

        def worth(tried: Sequence[Test], left: int = left) -> tuple[float, int]:
            mask = left & prune
            for t in tried:
                mask &= tests[t]
            q, m = counts(mask)
            return ((q + 1) / (q + m + 2), q)

        while len(rule) > 1 and (shorter := max(([*rule[:i], *rule[i + 1 :]] for i in range(len(rule))), key=worth)) and worth(shorter)[0] >= worth(rule)[0]:
            rule = shorter
        mask = left
        for t in rule:
            mask &= tests[t]
        q, m = counts(mask)
        held_q, held_m = counts(mask & prune)
        if not rule or q < least or not held_q or q < precision * (q + m) or held_q < precision * (held_q + held_m):
            break
        rules.append(tuple(rule))
        left &= ~mask
    return rules


def verdict(rules: Sequence[Rule]) -> Column:
    """1-based number of the first rule that holds, 0 if none: one ordered conditional expression."""
    chain = None
    for k, rule in enumerate(rules, 1):
        holds = reduce(and_, [t.column() for t in rule])
        chain = F.when(holds, k) if chain is None else chain.when(holds, k)
    return F.lit(0) if chain is None else chain.otherwise(0)


def fit(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS) -> list[Rule]:
    """Rules from a bounded sample of labelled documents that pass the base rule."""
    spread = F.xxhash64(F.col("doc_id"))
    picked = None
    for quality in (0, 1):
        some = labels.where((F.col("quality") == quality) & F.col("doc_id").isNotNull()).select("doc_id", (F.col("quality") == 0).alias("bad")).orderBy(spread, "doc_id").limit(fit_rows)
        picked = some if picked is None else picked.unionByName(some)
    # A document that is labelled both ways counts as bad.
    picked = picked.groupBy("doc_id").agg(F.max("bad").alias("bad"))
    # At most 2 * fit_rows ids: bounded, so it may be broadcast. The rows are written first, so that statistics are taken of them alone.
    sample = docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id").distinct()
    sample = common.materialise(sample.orderBy(spread, "doc_id", "text").limit(2 * fit_rows), "quality-sample")
    rows = [r.asDict() for r in with_statistics(sample).select("doc_id", "bad", "base_failed", *STATS).collect()]
    rows = [r for r in rows if not r.pop("base_failed")]
    common.discard(sample)
    rows.sort(key=lambda r: (zlib.crc32(str(r["doc_id"]).encode()), r["doc_id"], r["n_words"]))
    return learn_rules(rows)


def judge(docs: DataFrame, rules: Sequence[Rule]) -> DataFrame:
    """Documents with their statistics, ``base_failed``, ``rule`` (the first that holds) and ``kept``."""
    return with_statistics(docs).withColumn("rule", verdict(rules)).withColumn("kept", ~F.col("base_failed") & (F.col("rule") == 0))


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    rules = fit(docs, common.table(spark, sf_dir, "labels"))
    return judge(docs.select("doc_id", "text"), rules).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "rule")
