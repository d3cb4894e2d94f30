"""Functions that operators take: deterministic code, or an instruction with an output schema.

A semantic function may be a paid model. Models are plug-ins (``SemanticFn.run``); here only simulated
annotators stand in, deterministic and blind to references. Their numbers show that the plumbing works, never that a model is good.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from mediarel.sources import stored


@dataclass(frozen=True)
class DeterministicFn:
    """Ordinary code: a column expression over the row."""

    name: str
    expr: Callable[[], Column] = field(compare=False)


@dataclass(frozen=True)
class SemanticFn:
    """An instruction over one representation with a declared output.

    ``run(df, on, into)`` adds ``into``. ``witness`` says whether a bounded interval can establish a result
    (``bounded``) or only the whole source can (``global``). ``siblings`` are the same task over other representations.
    """

    name: str
    instruction: str
    modality: str
    output: str
    run: Callable[[DataFrame, str, str], DataFrame] = field(compare=False)
    witness: str = "bounded"
    source_time: bool = True
    siblings: dict[str, SemanticFn] = field(default_factory=dict, compare=False)
    #: (tokens, milliseconds of footage) of the call for a row, from the column ``on``; None: not metered.
    meter: Callable[[str], tuple[Column, Column]] | None = field(default=None, compare=False)
    #: A paid function's answers are written behind it, so that nothing that reads them calls it again.
    paid: bool = False

    def schema(self) -> T.DataType:
        return T.StructType.fromDDL(f"o {self.output}")["o"].dataType

    def key(self, payload: Column, version: str = "1") -> Column:
        """Idempotency key of a call: a retry finds the finished answer instead of paying again."""
        return F.sha2(F.concat_ws("\u0000", F.lit(self.name), F.lit(self.instruction), F.lit(version), payload), 256)


def compose(*steps: Callable[[Column], Column]) -> Callable[[Column], Column]:
    """Right to left, as in ``embed after suppress``."""

    def run(x: Column) -> Column:
        for step in reversed(steps):
            x = step(x)
        return x

    return run


def call_model(df: DataFrame, fn: SemanticFn, on: str, into: str, client: Callable[[], Callable[[list[str]], list]], folder: str | None = None, batch_rows: int = 32, version: str = "1") -> DataFrame:
    """Calls from executors: one client a task, ``batch_rows`` inputs at a time, and each distinct input once.

    Answers are stored under ``fn.key`` in ``folder`` with the ``calls`` and ``tokens`` they took, in a batch of their own for each run; an
    input whose answer is stored is not paid again, and a run that fails before its commit leaves no answers. Rows get ``into``,
    ``calls`` and ``tokens``; the answers' table is the ledger of what was paid.
    """
    spark = df.sparkSession
    at = f"{folder or stored.shared_folder(spark)}/answers/{hashlib.sha256(f'{fn.name}/{version}'.encode()).hexdigest()[:16]}"
    schema = T.StructType([T.StructField("_key", T.StringType()), T.StructField(into, fn.schema()), T.StructField("calls", T.LongType()), T.StructField("tokens", T.LongType())])

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        answer = client()
        for batch in batches:
            for start in range(0, len(batch), batch_rows):
                part = batch.iloc[start : start + batch_rows]
                texts = part["_payload"].astype(str).tolist()
                yield pd.DataFrame({"_key": part["_key"].tolist(), into: answer(texts), "calls": 1, "tokens": [len(t) // 4 + 1 for t in texts]})

    keyed = df.withColumn("_key", fn.key(F.col(on).cast("string"), version))
    asked = keyed.select("_key", F.col(on).cast("string").alias("_payload")).dropDuplicates(["_key"])
    known = stored.batches(spark, at, schema)
    stored.append_batch(asked.join(known.select("_key"), "_key", "left_anti").mapInPandas(run, schema), at)
    return keyed.join(stored.batches(spark, at, schema), "_key", "left").drop("_key")


#: Fixed values, derived from the published totals: tokens for 1000 source seconds and money for a million tokens.
FOOTAGE_TOKENS, NARRATION_TOKENS = 91_000, 8_500
USD_PER_MILLION = 0.25


def footage_tokens(ms: Column) -> Column:
    return F.ceil(ms * 91 / 1000).cast("bigint")


def narration_tokens(ms: Column) -> Column:
    return F.ceil(ms * 85 / 10000).cast("bigint")


def cost_usd(tokens: Column) -> Column:
    return F.round(tokens * F.lit(USD_PER_MILLION) / 1_000_000, 6)


def watching(on: str) -> tuple[Column, Column]:
    """Meter of a function over footage: what a row's clip takes."""
    ms = F.col(on)["clip_end_ms"] - F.col(on)["clip_start_ms"]
    return footage_tokens(ms), ms


def reading(on: str) -> tuple[Column, Column]:
    """Meter of a function over the narration of a whole source: it watches no footage."""
    return narration_tokens(F.col("duration_ms")), F.lit(0).cast("bigint")
