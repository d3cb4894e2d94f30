"""Shared helpers: intermediate tables in the cluster's shared folder, words, table access."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from mediarel.sources import stored

#: A word is a run of anything but space and the control characters 9 to 13.
WORD_SEPARATORS = " \t\n\x0b\x0c\r"
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
SEPARATOR_PATTERN = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def new_path(spark: SparkSession, name: str) -> str:
    """A fresh path in the cluster's shared folder; it is removed when the driver ends."""
    return stored.new_path(spark, name)


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage, survives lost executors."""
    path = new_path(df.sparkSession, name)
    back = stored.write(df, path)
    back._stored_at = path
    return back


@contextmanager
def small_batches(spark: SparkSession, rows: int = 1024) -> Iterator[None]:
    """Jobs started inside hand ``rows`` rows at a time to Python workers: whole texts are large, on either side of the pipe."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, str(rows))
    try:
        yield
    finally:
        spark.conf.set(key, before)


def discard(*frames: DataFrame) -> None:
    """Delete intermediate tables of ``materialise`` that nothing reads any more."""
    for df in frames:
        path = getattr(df, "_stored_at", None)
        if path:
            stored.remove(df.sparkSession, path)


_held: dict[str, Callable[[], object]] = {}


def claim(name: str, clear: Callable[[], object] | None = None) -> None:
    """In a worker process: what other operators have cached goes, so that reused workers hold one operator's cache at a time."""
    for other in [k for k in _held if k != name]:
        _held.pop(other)()
    if clear is not None:
        _held[name] = clear


def empty_if_null(text: Column) -> Column:
    return F.coalesce(text, F.lit(""))


def n_words(text: Column) -> Column:
    """Words of a text as a long; null and blank texts have none. Each word shrinks to one character."""
    each = r"[\x20\x09-\x0D]*+[^\x20\x09-\x0D]++[\x20\x09-\x0D]*+"
    return F.when(text.rlike(WORD_PATTERN), F.length(F.regexp_replace(text, each, "x")).cast("long")).otherwise(F.lit(0).cast("long"))


def ascii_lower(text: Column) -> Column:
    """A to Z only; every other character stays."""
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def slices(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.RecordBatch]:
    """Record batches in parts of at most ``rows`` rows, so that few texts are Python objects at a time."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def each_text(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[str | None]:
    """Texts of the last column, one at a time."""
    for part in slices(batches, rows):
        yield from part.column(part.num_columns - 1).to_pylist()


def each_text_of(batch: pa.Array, rows: int = 64) -> Iterator[str | None]:
    """Texts of an array, few of them as Python strings at a time."""
    for at in range(0, len(batch), rows):
        yield from batch.slice(at, rows).to_pylist()
