"""Media plans to DataFrames."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mediarel.functions.semantic import DeterministicFn, SemanticFn
from mediarel.plans import ir
from mediarel.sources.stored import barrier


@dataclass
class Account:
    """What a run of a plan took: a ledger row for each metered function, and seconds for each stage if ``timed``.

    Both need every function evaluated once, so what it returns is written and read back.
    """

    timed: bool = False
    ledger: list[DataFrame] = field(default_factory=list)
    seconds: list[tuple[str, float, int]] = field(default_factory=list)


def lower(node: ir.Node, account: Account | None = None) -> DataFrame:
    return _LOWER[type(node)](node, account)


def _column(fn: DeterministicFn | Column) -> Column:
    return fn.expr() if isinstance(fn, DeterministicFn) else fn


def _called(df: DataFrame, fn: SemanticFn, on: str, into: str, account: Account | None) -> DataFrame:
    if account is None or fn.meter is None:
        return barrier(fn.run(df, on, into)) if fn.paid else fn.run(df, on, into)
    tokens, watched = fn.meter(on)
    paid = barrier(fn.run(df.withColumns({"_tokens": tokens, "_watched_ms": watched}), on, into))
    sums = paid.agg(F.count("*").alias("calls"), F.coalesce(F.sum("_tokens"), F.lit(0)).cast("bigint").alias("tokens"), F.coalesce(F.sum("_watched_ms"), F.lit(0)).cast("bigint").alias("watched_ms"))
    account.ledger.append(sums.select(F.lit(fn.name).alias("fn"), F.lit(fn.modality).alias("modality"), "calls", "tokens", "watched_ms"))
    return paid.drop("_tokens", "_watched_ms")


def _map(n: ir.Map, account: Account | None) -> DataFrame:
    df = lower(n.child, account)
    return _called(df, n.fn, n.on, n.into, account) if isinstance(n.fn, SemanticFn) else df.withColumn(n.into, _column(n.fn))


def _filter(n: ir.Filter, account: Account | None) -> DataFrame:
    df = lower(n.child, account)
    if isinstance(n.predicate, SemanticFn):
        return _called(df, n.predicate, n.on, "_holds", account).where("_holds").drop("_holds")
    return df.where(n.predicate)


def _reduce(n: ir.Reduce, account: Account | None) -> DataFrame:
    df = lower(n.child, account)
    if not n.keys and callable(n.fn) and df.limit(n.max_group_rows + 1).count() > n.max_group_rows:
        raise ir.PlanError(f"a group function over an empty key would take more than {n.max_group_rows} rows into one task; give a key")
    if callable(n.fn):
        return n.fn(df, list(n.keys))
    return df.groupBy(*n.keys).agg(*[c.alias(name) for name, c in n.fn.items()])


def _unnest(n: ir.Unnest, account: Account | None) -> DataFrame:
    df = lower(n.child, account)
    kept = [c for c in df.columns if c != n.field]
    if n.ordinal:
        each = (F.posexplode_outer if n.outer else F.posexplode)(n.field).alias(n.ordinal, n.field)
    else:
        each = (F.explode_outer if n.outer else F.explode)(n.field).alias(n.field)
    return df.select(*kept, each)


def _join(n: ir.Join, account: Account | None) -> DataFrame:
    joined = lower(n.left, account).join(lower(n.right, account), n.on, n.how)
    return joined if n.score is None else joined.withColumn(n.keep_score, n.score)


def _view(n: ir.View, account: Account | None) -> DataFrame:
    v = F.col(n.v)
    clip = v.withField("clip_start_ms", v["clip_start_ms"] + F.col(n.start)).withField("clip_end_ms", v["clip_start_ms"] + F.col(n.end))
    return lower(n.child, account).withColumn(n.into, clip)


def _stage(n: ir.Stage, account: Account | None) -> DataFrame:
    df = lower(n.child, account)
    if account is None or not account.timed:
        return df
    began = time.monotonic()
    done = barrier(df)
    account.seconds.append((n.name, time.monotonic() - began, done.count()))
    return done


_LOWER = {
    ir.Input: lambda n, _: n.df,
    ir.Map: _map,
    ir.Filter: _filter,
    ir.Reduce: _reduce,
    ir.Unnest: _unnest,
    ir.Join: _join,
    ir.Resolve: lambda n, a: n.resolver(lower(n.child, a), list(n.within)),
    ir.View: _view,
    ir.Transcribe: lambda n, a: n.engine(lower(n.child, a), n.v, n.into),
    ir.Detect: lambda n, a: n.detector(lower(n.child, a), n.v, n.classes, n.into),
    ir.Track: lambda n, a: n.tracker(lower(n.child, a), n.detections, n.into),
    ir.Stage: _stage,
}
