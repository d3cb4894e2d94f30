"""Training-corpus pipeline: language, quality, near duplicates, mixing, tokens.

Every stage takes ``(spark, docs, sf_dir)`` and returns a DataFrame that is written as Parquet and read again as
the next stage's ``docs``. All stages but the last return the columns of ``documents``. Each works on all that
its predecessor kept:

* ``language``: texts whose language cannot be told go (no letters, or a corrected share below ``LEAST_SCORE``);
* ``quality``: texts that the base rule or the learned decision list rejects go;
* ``near_duplicates``: of each group linked by five-word shingles at 0.8 the smallest doc_id stays; where rows repeat a doc_id,
  each text counts alone, and of rows with the same doc_id and text one stays;
* ``mixing``: documents leave as often as the mix takes them (0, 1 or 2 times; those without words stay once);
* ``tokens``: ids of every text by forced-boundary BPE and the text decoded from them, in the place of ``text``.

Null texts go in the first stage; an empty table passes through all stages; extra columns are carried through the last stage, whatever
their names, but those named as the last stage's results, which take their place.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mediarel.llm import bpe, common, language, mixing, near_dup, quality

#: Below this share of n-grams in the best language a text has none.
LEAST_SCORE = 0.25


def _packed(docs: DataFrame) -> DataFrame:
    """Rows as one column, so that no column of theirs meets one of an operator's result."""
    return docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"))


def by_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = language.fit(docs.where(~language.held_out(F.col("doc_id"))).select("doc_id", "text", "lang"))
    told = language.predict(_packed(docs), model, text="_row.text")
    return told.where((F.col("lang_pred") != language.UNDETERMINED) & (F.col("score") >= LEAST_SCORE)).select("_row.*")


def by_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    rules = quality.fit(docs, common.table(spark, sf_dir, "labels"))
    return quality.judge(_packed(docs).select("_row", "_row.text"), rules).where("kept").select("_row.*")


def without_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    known = docs.where("doc_id IS NOT NULL")
    if known.groupBy("doc_id").count().where("count > 1").limit(1).count():
        # Every distinct (doc_id, text) gets a number in that order, which stands for it as an id.
        texts = known.select("doc_id", "text").distinct().orderBy("doc_id", "text").withColumn("_row", F.monotonically_increasing_id())
        texts = common.materialise(texts, "pipeline-texts")
        linked = near_dup.link(texts.select(F.col("_row").alias("doc_id"), "text"))
        alone = texts.join(linked.where("kept").select(F.col("doc_id").alias("_row")), "_row", "left_semi").alias("alone")
        one = known.dropDuplicates(["doc_id", "text"]).alias("one")
        one = one.join(alone, (F.col("one.doc_id") == F.col("alone.doc_id")) & F.col("one.text").eqNullSafe(F.col("alone.text")), "left_semi")
        return one.unionByName(docs.where("doc_id IS NULL")).select(*[F.col(f"`{c}`") for c in docs.columns])
    linked = near_dup.link(docs)
    return docs.join(linked.where(~F.col("kept")).select("doc_id"), "doc_id", "left_anti").select(*[F.col(f"`{c}`") for c in docs.columns])


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    rows = _packed(docs).select("_row", "_row.doc_id", "_row.source")
    taken = mixing.mix(rows, size=common.n_words(F.col("_row.text")), tie=F.xxhash64("_row.text"))
    return mixing.repeat_copies(taken, ["_row"]).select("_row.*")


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe.encoded(docs)


STAGES = [
    ("language", by_language),
    ("quality", by_quality),
    ("near_duplicates", without_near_duplicates),
    ("mixing", mixed),
    ("tokens", tokens),
]

#: BPE and learned models are no SQL; tests hold the rows of every stage against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    for place, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if place < len(STAGES) - 1:
            docs = common.materialise(docs, f"pipeline-{name}")
    return docs
