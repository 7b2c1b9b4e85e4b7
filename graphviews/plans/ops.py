"""Plan operators.

A *graph plan* has vertex scans, walks and the relational operators.  A *join plan*
has no walks: they are joins with edge scans, and transitive joins.  A *flat plan* is
a join plan whose leaves carry the properties that the query needs.
"""

from __future__ import annotations

from dataclasses import dataclass, fields, replace
from typing import Any

OUT, IN, BOTH = "out", "in", "both"


class Node:
    """Base of plan operators; children are the fields that are operators."""

    def children(self) -> list[Node]:
        return [getattr(self, f.name) for f in fields(self) if isinstance(getattr(self, f.name), Node)]

    def with_children(self, new: list[Node]) -> Node:
        names = [f.name for f in fields(self) if isinstance(getattr(self, f.name), Node)]
        return replace(self, **dict(zip(names, new)))

    def walk(self):
        yield self
        for c in self.children():
            yield from c.walk()


def rewritten(node: Node, rule) -> Node:
    """Apply a rule bottom-up; it gives a node or None."""
    node = node.with_children([rewritten(c, rule) for c in node.children()])
    return rule(node) or node


@dataclass(frozen=True)
class Dual(Node):
    """One row without columns."""


@dataclass(frozen=True)
class ScanVertices(Node):
    var: str
    labels: tuple[str, ...] = ()
    props: tuple[str, ...] = ()


@dataclass(frozen=True)
class ScanEdges(Node):
    v: str
    v_labels: tuple[str, ...]
    e: str
    types: tuple[str, ...]
    w: str
    w_labels: tuple[str, ...]
    direction: str = OUT
    props: tuple[tuple[str, str], ...] = ()
    ends: bool = True  # whether the scan itself joins the vertices at its ends


@dataclass(frozen=True)
class Walk(Node):
    child: Node
    v: str
    e: str
    types: tuple[str, ...]
    w: str
    labels: tuple[str, ...] = ()
    direction: str = OUT


@dataclass(frozen=True)
class WalkVar(Node):
    child: Node
    v: str
    e: str
    types: tuple[str, ...]
    w: str
    labels: tuple[str, ...] = ()
    direction: str = OUT
    low: int = 1
    up: int | None = None
    mode: str = "trail"


@dataclass(frozen=True)
class TransitiveJoin(Node):
    """Rows of child with the paths that start at v; edges is an edge scan.

    ends, if given, has the only vertices w that matter; paths are then walked back from them.
    """

    child: Node
    edges: Node
    v: str
    e: str
    w: str
    low: int
    up: int | None
    mode: str
    direction: str
    ends: Node | None = None


@dataclass(frozen=True)
class Select(Node):
    child: Node
    cond: Any


@dataclass(frozen=True)
class Project(Node):
    child: Node
    items: tuple[tuple[str, Any], ...]
    keep: tuple[tuple[str, str], ...] = ()


@dataclass(frozen=True)
class Distinct(Node):
    child: Node


@dataclass(frozen=True)
class Group(Node):
    child: Node
    keys: tuple[tuple[str, Any], ...]
    outs: tuple[tuple[str, Any], ...]
    keep: tuple[tuple[str, str], ...] = ()


@dataclass(frozen=True)
class SortTop(Node):
    """Sort, skip and limit in one; ties are broken by all columns."""

    child: Node
    keys: tuple[tuple[Any, bool], ...]
    skip: int = 0
    limit: int | None = None


@dataclass(frozen=True)
class Unwind(Node):
    child: Node
    items: Any
    name: str
    place: str | None = None


@dataclass(frozen=True)
class NaturalJoin(Node):
    left: Node
    right: Node


@dataclass(frozen=True)
class LeftOuter(Node):
    left: Node
    right: Node
    cond: Any = None


@dataclass(frozen=True)
class Semi(Node):
    left: Node
    right: Node


@dataclass(frozen=True)
class Anti(Node):
    left: Node
    right: Node


@dataclass(frozen=True)
class Union(Node):
    left: Node
    right: Node


def kinds(node: Node) -> dict[str, str]:
    """Variables of an operator's result and their kinds."""
    match node:
        case Dual():
            return {}
        case ScanVertices(var=v):
            return {v: "vertex"}
        case ScanEdges(v=v, e=e, w=w):
            return {v: "vertex", e: "edge", w: "vertex"}
        case Walk(child=c, e=e, w=w):
            return {**kinds(c), e: "edge", w: "vertex"}
        case WalkVar(child=c, e=e, w=w) | TransitiveJoin(child=c, e=e, w=w):
            return {**kinds(c), e: "path", w: "vertex"}
        case Project(child=c, items=items):
            return _named(kinds(c), items)
        case Group(child=c, keys=keys, outs=outs):
            return {**_named(kinds(c), keys), **{n: "value" for n, _ in outs}}
        case Unwind(child=c, name=n, place=p):
            return {**kinds(c), n: "value", **({p: "value"} if p else {})}
        case NaturalJoin(left=a, right=b) | LeftOuter(left=a, right=b):
            return {**kinds(b), **kinds(a)}
        case Semi(left=a) | Anti(left=a) | Union(left=a):
            return kinds(a)
        case Select(child=c) | Distinct(child=c) | SortTop(child=c):
            return kinds(c)
    raise TypeError(node)


def _named(inside: dict[str, str], items) -> dict[str, str]:
    from graphviews.plans.expr import Var

    return {n: inside.get(e.name, "value") if isinstance(e, Var) else "value" for n, e in items}


def show(node: Node, depth: int = 0) -> str:
    """The plan as indented text."""
    own = ", ".join(f"{f.name}={getattr(node, f.name)!r}" for f in fields(node) if not isinstance(getattr(node, f.name), Node))
    return "\n".join(["  " * depth + f"{type(node).__name__}({own})", *(show(c, depth + 1) for c in node.children())])
