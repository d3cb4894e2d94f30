"""Fluent media plans: ``MediaFrame`` builds nodes, ``to_df`` lowers them."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from functools import reduce
from typing import Any

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from mediarel.functions.semantic import DeterministicFn, SemanticFn
from mediarel.plans import ir, lower, rules


class MediaFrame:
    """A media plan under construction. Every method returns a new one."""

    def __init__(self, node: ir.Node):
        self.node = node

    @classmethod
    def scan(cls, spark: SparkSession, path_or_table: str, fmt: str = "parquet") -> MediaFrame:
        df = spark.table(path_or_table) if fmt == "table" else spark.read.format(fmt).load(path_or_table)
        return cls(ir.Input(df, path_or_table))

    @classmethod
    def of(cls, df: DataFrame, name: str = "input") -> MediaFrame:
        return cls(ir.Input(df, name))

    def derive(self, into: dict[str, Any], on: str | None = None) -> MediaFrame:
        node = self.node
        for name, fn in into.items():
            node = ir.Map(node, F.expr(fn) if isinstance(fn, str) else fn, name, on)
        return MediaFrame(node)

    def keep(self, predicate: Column | str | SemanticFn, on: str | None = None) -> MediaFrame:
        return MediaFrame(ir.Filter(self.node, F.expr(predicate) if isinstance(predicate, str) else predicate, on))

    def fold(self, keys: Sequence[str], fn: dict[str, Column] | Callable, max_group_rows: int = 1_000_000) -> MediaFrame:
        return MediaFrame(ir.Reduce(self.node, tuple(keys), fn, max_group_rows))

    def unnest(self, field: str, outer: bool = False, ordinal: str | None = None) -> MediaFrame:
        return MediaFrame(ir.Unnest(self.node, field, outer, ordinal))

    def pair(self, other: MediaFrame, on: Any, score: Column | None = None, keep_score: str = "match_score", how: str = "inner") -> MediaFrame:
        return MediaFrame(ir.Join(self.node, other.node, on, score, keep_score, how))

    def settle(self, resolver: Callable[[DataFrame, list[str]], DataFrame], within: Sequence[str]) -> MediaFrame:
        return MediaFrame(ir.Resolve(self.node, resolver, tuple(within)))

    def view(self, v: str, start: str, end: str, into: str) -> MediaFrame:
        return MediaFrame(ir.View(self.node, v, start, end, into))

    def transcribe(self, v: str, into: str, engine: Callable) -> MediaFrame:
        return MediaFrame(ir.Transcribe(self.node, v, into, engine))

    def detect(self, v: str, classes: Sequence[str], into: str, detector: Callable) -> MediaFrame:
        return MediaFrame(ir.Detect(self.node, v, tuple(classes), into, detector))

    def track(self, detections: str, into: str, tracker: Callable) -> MediaFrame:
        return MediaFrame(ir.Track(self.node, detections, into, tracker))

    def rewrite(self, *applied) -> MediaFrame:
        return MediaFrame(rules.rewrite(self.node, list(applied)))

    def stage(self, name: str) -> DataFrame:
        """The intermediate relation of this name."""
        for n in self.node.walk():
            if isinstance(n, ir.Stage) and n.name == name:
                return lower.lower(n)
        raise ir.PlanError(f"the plan has no stage {name}; it has {self.stages()}")

    def stages(self) -> list[str]:
        return list(dict.fromkeys(n.name for n in self.node.walk() if isinstance(n, ir.Stage)))

    def to_df(self) -> DataFrame:
        return lower.lower(self.node)

    def metered(self) -> tuple[DataFrame, DataFrame]:
        """(result, ledger): the plan is run, each metered function once; the ledger has fn, modality, calls, tokens, watched_ms."""
        account = lower.Account()
        done = lower.lower(self.node, account)
        if not account.ledger:
            return done, done.sparkSession.createDataFrame([], "fn string, modality string, calls bigint, tokens bigint, watched_ms bigint")
        return done, reduce(DataFrame.unionByName, account.ledger)

    def timed(self) -> tuple[DataFrame, list[tuple[str, float, int]]]:
        """(result, seconds and rows of each stage from a cold start): every stage is written before the next one reads it."""
        account = lower.Account(timed=True)
        done = lower.lower(ir.Stage(self.node, "result"), account)
        return done, account.seconds

    def explain(self) -> str:
        return ir.pretty(self.node)


__all__ = ["DeterministicFn", "MediaFrame", "SemanticFn"]
