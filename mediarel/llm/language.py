"""Language identification with language-bitmask n-gram filters.

A bit-sliced Bloom filter has one slot array whose entries are bitmasks of languages. An n-gram
sets the bits of its languages at a few slots; the AND of its slots gives every language that
contains it, at once. A text adds up, for each language, the n-grams whose mask has the bit. The
share of set bits of a language gives its false-positive rate, which is taken out of its count:
``(hits - n * f) / (1 - f)``. The language with the largest corrected share wins.

Fitting reads at most ``FIT_DOCS`` labelled documents a language, those with the smallest hash of
their id, whole (a documented bound); an n-gram belongs to a language if at least ``least_share`` of
those contain it. Prediction covers every whole text in numpy blocks of bounded size.

Defined cases: a null text or one without letters is ``und`` with score 0; ties go to the
smaller language name; no labelled text at all makes every text ``und``; up to 64 languages share
a slice, more take further slices; repeated rows are judged alike; an empty table gives an empty result;
other columns pass through, and columns named ``lang_pred`` or ``score`` are replaced.
"""

from __future__ import annotations

import unicodedata
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from mediarel.llm import common

UNDETERMINED = "und"
#: Labelled documents of a language that a filter is fitted on at most.
FIT_DOCS = 1500
#: Languages that a filter tells apart at most, those with the most labelled texts: a bound on its size and on what reaches the driver.
MOST_LANGUAGES = 1024
NGRAM = (2, 3, 4)
SLOTS = 1 << 20
PROBES = 3
#: Characters that one numpy block holds (a longer text is cut into blocks whose counts add up).
BLOCK_CHARS = 1 << 20
_ODD = np.uint64(0x9E3779B97F4A7C15)
_MIX = np.uint64(0xFF51AFD7ED558CCD)


def _letters(text: str) -> np.ndarray:
    """Code points of the lower-cased text; runs of other characters than letters become one 0."""
    points = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    kept = np.where(_is_letter(points), points, np.uint32(0))
    return kept[(kept != 0) | np.concatenate(([True], kept[:-1] != 0))] if len(kept) else kept


def _table() -> np.ndarray:
    return np.array([unicodedata.category(chr(c))[0] == "L" for c in range(0x110000)], dtype=bool)


_LETTER: np.ndarray | None = None


def _is_letter(points: np.ndarray) -> np.ndarray:
    global _LETTER
    if _LETTER is None:
        _LETTER = _table()
    return _LETTER[points]


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(33))) * _MIX
    return x ^ (x >> np.uint64(29))


def ngram_hashes(letters: np.ndarray, n: int) -> np.ndarray:
    """64-bit hashes of the n-grams that touch a letter; word edges (0) belong to n-grams."""
    if len(letters) < n:
        return np.empty(0, dtype=np.uint64)
    with np.errstate(over="ignore"):
        wide = letters.astype(np.uint64) + np.uint64(1)
        total = np.full(len(letters) - n + 1, n, dtype=np.uint64)
        for k in range(n):
            total = total * _ODD + wide[k : len(letters) - n + 1 + k]
        return _mixed(total)


def _slots(hashes: np.ndarray, n_slots: int, probes: int) -> list[np.ndarray]:
    """Double hashing over a power of two."""
    first, second = hashes & np.uint64(0xFFFFFFFF), (hashes >> np.uint64(32)) | np.uint64(1)
    with np.errstate(over="ignore"):
        return [((first + np.uint64(i) * second) & np.uint64(n_slots - 1)).astype(np.int64) for i in range(probes)]


@dataclass
class BitmaskFilter:
    """Bit-sliced Bloom filter: ``slices[s][slot]`` holds the bits of languages ``64 s`` to ``64 s + 63``."""

    languages: list[str]
    slices: np.ndarray
    probes: int = PROBES

    @classmethod
    def build(cls, languages: Iterable[str], grams: Iterable[tuple[int, int]], slots: int = SLOTS, probes: int = PROBES) -> BitmaskFilter:
        """``grams``: pairs of a signed 64-bit hash and the place of its language."""
        names = list(languages)
        slices = np.zeros((max(1, -(-len(names) // 64)), slots), dtype=np.uint64)
        pairs = np.array(list(grams), dtype=np.int64).reshape(-1, 2)
        for place in range(len(names)):
            hashes = pairs[pairs[:, 1] == place, 0].view(np.uint64) if len(pairs) else np.empty(0, np.uint64)
            for at in _slots(np.ascontiguousarray(hashes), slots, probes):
                slices[place // 64, at] |= np.uint64(1) << np.uint64(place % 64)
        return cls(names, slices, probes)

    def compact(self) -> BitmaskFilter:
        """The same bits in the narrowest entries: less memory to walk through."""
        kind = np.uint8 if len(self.languages) <= 8 else np.uint16 if len(self.languages) <= 16 else np.uint64
        return BitmaskFilter(self.languages, self.slices.astype(kind), self.probes)

    def masks(self, hashes: np.ndarray) -> np.ndarray:
        """For each hash the languages that contain it: (slices, hashes)."""
        found = None
        for at in _slots(hashes, self.slices.shape[1], self.probes):
            found = self.slices[:, at] if found is None else found & self.slices[:, at]
        return found

    def hits(self, hashes: np.ndarray) -> np.ndarray:
        """N-grams of each language."""
        masks = self.masks(hashes)
        if len(self.languages) <= 8:
            by_mask = np.bincount(masks[0], minlength=256)
            return np.array([by_mask[(np.arange(256) >> k) & 1 == 1].sum() for k in range(len(self.languages))], dtype=np.int64)
        return np.array([np.count_nonzero(masks[k // 64] >> masks.dtype.type(k % 64) & masks.dtype.type(1)) for k in range(len(self.languages))], dtype=np.int64)

    def false_rates(self) -> np.ndarray:
        fill = [np.count_nonzero(self.slices[k // 64] >> self.slices.dtype.type(k % 64) & self.slices.dtype.type(1)) / self.slices.shape[1] for k in range(len(self.languages))]
        return np.array(fill, dtype=float) ** self.probes

    def classify(self, text: str | None, rates: np.ndarray, orders: tuple[int, ...] = NGRAM) -> tuple[str, float]:
        letters = _letters(text) if text else np.empty(0, dtype=np.uint32)
        if not self.languages or not letters.any():
            return UNDETERMINED, 0.0
        total, n = np.zeros(len(self.languages), dtype=np.int64), 0
        padded = np.concatenate((np.zeros(1, np.uint32), letters, np.zeros(1, np.uint32)))
        for start in range(0, len(padded), BLOCK_CHARS):
            for order in orders:
                block = padded[start : start + BLOCK_CHARS + order - 1]
                hashes = ngram_hashes(block, order)
                total += self.hits(hashes)
                n += len(hashes)
        share = np.clip((total - n * rates) / np.maximum(n * (1 - rates), 1e-9), 0.0, 1.0)
        best = int(np.argmax(share))
        return self.languages[best], float(share[best])


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string")) % 4 == 2, F.lit(False))


def fit(docs: DataFrame, fit_docs: int = FIT_DOCS, orders: tuple[int, ...] = NGRAM, least_share: float = 0.02, slots: int = SLOTS) -> BitmaskFilter:
    """Filter of the languages in ``docs`` (doc_id, text, lang): rows that may be learned from."""
    known = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull())
    # Values of ``lang`` that fewer labelled texts hold are no language to learn once there are more than ``MOST_LANGUAGES``.
    counts = known.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(MOST_LANGUAGES).collect()
    names = sorted(r["lang"] for r in counts)
    if not names:
        return BitmaskFilter.build([], [], slots=8)
    # Hashes below a cut that leaves about four times the documents wanted: of a language with most of the rows few are ranked.
    cut = {r["lang"]: min((1 << 63) - 1, (1 << 66) * fit_docs // r["count"] - (1 << 63)) for r in counts}
    places = docs.sparkSession.createDataFrame([(name, place, cut[name]) for place, name in enumerate(names)], "lang string, place int, cut bigint")
    by_hash = Window.partitionBy("lang").orderBy(F.xxhash64("doc_id"), "doc_id")
    few = known.select("doc_id", "lang").join(F.broadcast(places), "lang").where(F.xxhash64("doc_id") <= F.col("cut")).select("doc_id", "lang", "place").distinct()
    picked = few.withColumn("turn", F.row_number().over(by_hash)).where(F.col("turn") <= fit_docs).select("doc_id", "lang", "place")
    # At most fit_docs ids a language, so the join may broadcast them.
    texts = known.select("doc_id", "lang", "text").join(F.broadcast(picked), ["doc_id", "lang"]).select("place", "text")

    def grams(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.claim("language")
        for part in common.slices(batches, 64):
            for place, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                letters = np.concatenate((np.zeros(1, np.uint32), _letters(text), np.zeros(1, np.uint32)))
                found = np.unique(np.concatenate([ngram_hashes(letters, n) for n in orders]))
                yield pa.RecordBatch.from_arrays([pa.array(found.view(np.int64)), pa.array(np.full(len(found), place, dtype=np.int32))], names=["gram", "place"])

    sizes = texts.groupBy("place").agg(F.count("*").alias("docs"))
    kept = (
        texts.mapInArrow(grams, "gram long, place int")
        .groupBy("gram", "place")
        .agg(F.count("*").alias("seen"))
        .join(F.broadcast(sizes), "place")
        .where(F.col("seen") >= F.greatest(F.lit(2), F.ceil(F.col("docs") * least_share)))
        .select("gram", "place")
    )
    # N-grams in a fixed share of the fitted documents: their number has a bound that no table size moves.
    return BitmaskFilter.build(names, ((r["gram"], r["place"]) for r in kept.toLocalIterator()), slots=slots)


def predict(docs: DataFrame, model: BitmaskFilter, orders: tuple[int, ...] = NGRAM, text: str = "text") -> DataFrame:
    """``docs`` with ``lang_pred`` and ``score``, replacing columns of these names."""
    kept = docs.drop("lang_pred", "score")
    narrow, rates = model.compact(), model.false_rates()
    sent = docs.sparkSession.sparkContext.broadcast((narrow.languages, narrow.slices, narrow.probes, rates))

    # One text costs far more than its transport: plain rows in small batches keep less of them in memory than Arrow's.
    held: list[BitmaskFilter] = []

    def told(value: str | None) -> tuple[str, float]:
        languages, slices, probes, rates = sent.value
        if not held:
            common.claim("language")
            held.append(BitmaskFilter(languages, slices, probes))
        return held[0].classify(value, rates, orders)

    classify = F.udf(told, T.StructType([T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())]), useArrow=False)
    return kept.withColumn("_lang", classify(F.col(text))).select(*kept.columns, "_lang.lang_pred", "_lang.score")


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    model = fit(docs.where(~held_out(F.col("doc_id"))).select("doc_id", "text", "lang"))
    return predict(docs.select("doc_id", "text"), model).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
