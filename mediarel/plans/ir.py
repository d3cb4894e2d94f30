"""Nodes of media plans: one frozen value for each operator of the algebra."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, fields, replace
from typing import Any

from pyspark.sql import Column, DataFrame

from mediarel.functions.semantic import DeterministicFn, SemanticFn


class PlanError(ValueError):
    """A plan or a rewrite that its preconditions forbid."""


@dataclass(frozen=True, eq=False)
class Node:
    @property
    def children(self) -> tuple[Node, ...]:
        return tuple(v for f in fields(self) if isinstance(v := getattr(self, f.name), Node))

    def with_children(self, change: Callable[[Node], Node]) -> Node:
        new = {f.name: change(v) for f in fields(self) if isinstance(v := getattr(self, f.name), Node)}
        return replace(self, **new) if any(new[k] is not getattr(self, k) for k in new) else self

    def walk(self) -> Iterator[Node]:
        yield self
        for c in self.children:
            yield from c.walk()


@dataclass(frozen=True, eq=False)
class Input(Node):
    df: DataFrame
    name: str = "input"


@dataclass(frozen=True, eq=False)
class Map(Node):
    child: Node
    fn: DeterministicFn | SemanticFn | Column
    into: str
    on: str | None = None


@dataclass(frozen=True, eq=False)
class Filter(Node):
    child: Node
    predicate: Column | SemanticFn
    on: str | None = None


@dataclass(frozen=True, eq=False)
class Reduce(Node):
    """``fn``: aggregate columns by name, or a group function ``run(df, keys) -> df``. An empty key is one task; ``max_group_rows`` guards it."""

    child: Node
    keys: tuple[str, ...]
    fn: Any
    max_group_rows: int = 1_000_000


@dataclass(frozen=True, eq=False)
class Unnest(Node):
    child: Node
    field: str
    outer: bool = False
    ordinal: str | None = None


@dataclass(frozen=True, eq=False)
class Join(Node):
    left: Node
    right: Node
    on: Any
    score: Column | None = None
    keep_score: str = "match_score"
    how: str = "inner"


@dataclass(frozen=True, eq=False)
class Resolve(Node):
    child: Node
    resolver: Any
    within: tuple[str, ...]


@dataclass(frozen=True, eq=False)
class View(Node):
    child: Node
    v: str
    start: str
    end: str
    into: str


@dataclass(frozen=True, eq=False)
class Transcribe(Node):
    child: Node
    v: str
    into: str
    engine: Callable[[DataFrame, str, str], DataFrame]


@dataclass(frozen=True, eq=False)
class Detect(Node):
    child: Node
    v: str
    classes: tuple[str, ...]
    into: str
    detector: Callable[[DataFrame, str, tuple[str, ...], str], DataFrame]


@dataclass(frozen=True, eq=False)
class Track(Node):
    child: Node
    detections: str
    into: str
    tracker: Callable[[DataFrame, str, str], DataFrame]


@dataclass(frozen=True, eq=False)
class Stage(Node):
    """A named intermediate relation that users can look at."""

    child: Node
    name: str


#: Granularity of a node's rows where the operator changes it.
_GRANULARITY = {View: "clip", Detect: "frame", Track: "track"}


def granularity(node: Node) -> str:
    for n in node.walk():
        if type(n) in _GRANULARITY:
            return _GRANULARITY[type(n)]
    return "video"


def pretty(node: Node, depth: int = 0) -> str:
    told = []
    for f in fields(node):
        v = getattr(node, f.name)
        if isinstance(v, Node) or isinstance(v, DataFrame) or v is None:
            continue
        told.append(f"{f.name}={getattr(v, 'name', None) or (v if isinstance(v, str | tuple | bool | int) else type(v).__name__)}")
    line = "  " * depth + f"{type(node).__name__}({', '.join(told)})"
    return "\n".join([line, *(pretty(c, depth + 1) for c in node.children)])
