"""Approximate rewrites of media plans. Each keeps the output schema; values may change."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mediarel.functions.geometry import pad_window
from mediarel.functions.semantic import SemanticFn
from mediarel.operators import intervals
from mediarel.plans import ir


def rewrite(plan: ir.Node, rules: list) -> ir.Node:
    for rule in rules:
        plan = rule.apply(plan)
    return plan


def _once(plan: ir.Node, wanted: Callable[[ir.Node], bool], change: Callable[[ir.Node], ir.Node], what: str) -> ir.Node:
    hit = 0

    def visit(node: ir.Node) -> ir.Node:
        nonlocal hit
        if wanted(node):
            hit += 1
            return change(node)
        return node.with_children(visit)

    done = visit(plan)
    if not hit:
        raise ir.PlanError(f"{what}: no operator of the plan fits")
    return done


def same_schema(a: SemanticFn, b: SemanticFn) -> bool:
    return a.schema().simpleString() == b.schema().simpleString() and a.source_time == b.source_time


@dataclass(frozen=True)
class SubstituteModality:
    """Answer from another representation of the same source. Catalyst then never reads the first one."""

    from_: str
    to: str

    def apply(self, plan: ir.Node) -> ir.Node:
        def wanted(n: ir.Node) -> bool:
            return isinstance(n, ir.Map | ir.Filter) and isinstance(fn := _fn(n), SemanticFn) and n.on == self.from_

        def change(n: ir.Node) -> ir.Node:
            other = _fn(n).siblings.get(self.to)
            if other is None:
                raise ir.PlanError(f"{_fn(n).name} has no form over {self.to}")
            if not same_schema(_fn(n), other):
                raise ir.PlanError(f"{other.name} returns another schema than {_fn(n).name}")
            return ir.Map(n.child, other, n.into, self.to) if isinstance(n, ir.Map) else ir.Filter(n.child, other, self.to)

        return _once(plan, wanted, change, "modality substitution")


def _fn(n: ir.Node):
    return n.fn if isinstance(n, ir.Map) else n.predicate


@dataclass(frozen=True)
class PushdownWindows:
    """Let a model watch only windows around candidates that a cheaper representation names.

    Candidates, padded and clamped, are coalesced by source; the same function runs on the clips; its
    results go back to source time and are reconciled by source. Sources without candidates come back with an
    empty result, and source attributes are attached again.
    """

    cand: SemanticFn
    cand_on: str
    before_ms: int
    after_ms: int
    reconcile: Callable[[DataFrame, list[str], str], DataFrame]
    keys: tuple[str, ...] = ("source_id",)
    #: Key columns that candidates carry, beside those of the source: several instructions over one relation.
    lift: tuple[str, ...] = ()
    duration: str = "duration_ms"
    restore_sources: bool = True

    def apply(self, plan: ir.Node) -> ir.Node:
        def wanted(n: ir.Node) -> bool:
            return isinstance(n, ir.Map) and isinstance(n.fn, SemanticFn) and n.on != self.cand_on

        return _once(plan, wanted, self._narrowed, "candidate pushdown")

    def _narrowed(self, n: ir.Map) -> ir.Node:
        if n.fn.witness != "bounded":
            raise ir.PlanError(f"{n.fn.name} needs the whole source: no window can establish its result")
        source, keys = n.child, list(self.keys)
        found = ir.Unnest(ir.Map(source, self.cand, "_c", self.cand_on), "_c")
        low, high = pad_window(F.col("_c.start_ms"), F.col("_c.end_ms"), self.before_ms, self.after_ms, F.col(self.duration))
        for name in self.lift:
            found = ir.Map(found, F.col(f"_c.{name}"), name)
        padded = ir.Map(ir.Map(ir.Stage(found, "candidates"), low, "start_ms"), high, "end_ms")
        real = ir.Filter(padded, F.col("start_ms") < F.col("end_ms"))
        windows = ir.Stage(ir.Resolve(real, lambda df, within: intervals.coalesce(df, within), (*self.keys, *self.lift)), "windows")
        media = ir.Resolve(source, lambda df, within: df.select(*within, n.on), self.keys)
        clips = ir.Stage(ir.View(ir.Join(windows, media, keys), n.on, "start_ms", "end_ms", "_clip"), "clips")
        watched = ir.Stage(ir.Map(clips, n.fn, n.into, "_clip"), "watched")
        settled = ir.Reduce(watched, (*self.keys, *self.lift), lambda df, by: self.reconcile(df, by, n.into))
        if self.lift:
            # Results of all instructions on a source are one collection again.
            settled = ir.Reduce(settled, self.keys, lambda df, by: df.groupBy(*by).agg(F.array_sort(F.flatten(F.collect_list(n.into))).alias(n.into)))
        if not self.restore_sources:
            return settled
        joined = ir.Join(source, settled, keys, how="left")
        empty = F.coalesce(F.col(n.into), F.array().cast(n.fn.output)) if n.fn.output.startswith("array") else F.col(n.into)
        return ir.Map(joined, empty, n.into)


@dataclass(frozen=True)
class DecomposeAssociation:
    """Replace one call over a whole group of feeds by detect, suppress and embed, track, pair, settle and report."""

    detect: Callable[[DataFrame, str, tuple[str, ...], str], DataFrame]
    refine: Callable[[DataFrame, str, str], DataFrame]
    track: Callable[[DataFrame, str, str], DataFrame]
    pair: Callable[[DataFrame], DataFrame]
    settle: Callable[[DataFrame, list[str]], DataFrame]
    report: Callable[[DataFrame], DataFrame]
    classes: tuple[str, ...] = ()
    on: str = "v"
    within: tuple[str, ...] = ("scene_id", "left_source", "right_source")

    def apply(self, plan: ir.Node) -> ir.Node:
        def wanted(n: ir.Node) -> bool:
            return isinstance(n, ir.Unnest) and isinstance(n.child, ir.Reduce) and getattr(n.child.fn, "associates", False)

        def change(n: ir.Node) -> ir.Node:
            detected = ir.Stage(ir.Detect(n.child.child, self.on, self.classes, "_d", self.detect), "detections")
            refined = ir.Stage(ir.Resolve(detected, lambda df, _: self.refine(df, "_d", "_d"), ()), "refined")
            tracks = ir.Stage(ir.Unnest(ir.Track(refined, "_d", "_t", self.track), "_t"), "tracks")
            pairs = ir.Stage(ir.Resolve(tracks, lambda df, _: self.pair(df), ()), "pairs")
            matches = ir.Stage(ir.Resolve(pairs, self.settle, self.within), "matches")
            return ir.Stage(ir.Resolve(matches, lambda df, _: self.report(df), ()), "associations")

        return _once(plan, wanted, change, "association decomposition")


@dataclass(frozen=True)
class OrderFilters:
    """Cheap filters first: a deterministic filter above a semantic map or filter that it does not read moves below it."""

    def apply(self, plan: ir.Node) -> ir.Node:
        def visit(node: ir.Node) -> ir.Node:
            node = node.with_children(visit)
            if isinstance(node, ir.Filter) and isinstance(node.predicate, Column):
                below = node.child
                if isinstance(below, ir.Filter) and isinstance(below.predicate, SemanticFn):
                    return ir.Filter(visit(ir.Filter(below.child, node.predicate)), below.predicate, below.on)
                if isinstance(below, ir.Map) and isinstance(below.fn, SemanticFn) and below.into not in _names(node.predicate):
                    return ir.Map(visit(ir.Filter(below.child, node.predicate)), below.fn, below.into, below.on)
            return node

        return visit(plan)


def _names(column: Column) -> set[str]:
    import re

    return set(re.findall(r"\w+", str(column)))
