"""Expressions over variables, and their columns.

A vertex or edge variable ``v`` is an id column ``v``; its property ``k`` is the
column ``v__k`` once the plan is flat.  Metadata are pseudo-properties whose keys
begin with ``@``.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, fields, is_dataclass
from typing import Any

from pyspark.sql import Column
from pyspark.sql import functions as F

LABELS, TYPE, SOURCE, TARGET = "@labels", "@type", "@src", "@trg"


class PlanError(ValueError):
    """A query that has no meaning: raised when it is compiled."""


def flat(var: str, key: str) -> str:
    return f"{var}__{key}"


def column(name: str) -> Column:
    return F.col(f"`{name}`")


@dataclass(frozen=True)
class Lit:
    value: Any


@dataclass(frozen=True)
class Var:
    name: str


@dataclass(frozen=True)
class Prop:
    """Property of a variable; null where the element lacks it."""

    var: str
    key: str


@dataclass(frozen=True)
class HasLabels:
    var: str
    labels: tuple[str, ...]


@dataclass(frozen=True)
class Op:
    name: str
    args: tuple


@dataclass(frozen=True)
class Call:
    name: str
    args: tuple


@dataclass(frozen=True)
class Each:
    """Higher-order expression over a list: all, any, none, filter or transform."""

    kind: str
    name: str
    items: Any
    body: Any


@dataclass(frozen=True)
class Agg:
    name: str
    arg: Any
    distinct: bool = False
    extra: Any = None


@dataclass(frozen=True)
class Pattern:
    """A pattern as a condition: at least one match; plan is compiled by the builder."""

    plan: Any


def parts(e: Any) -> Iterator[Any]:
    """e and all expressions inside it."""
    yield e
    if is_dataclass(e) and not isinstance(e, Pattern):
        for f in fields(e):
            value = getattr(e, f.name)
            for x in value if isinstance(value, tuple) else (value,):
                if is_dataclass(x):
                    yield from parts(x)


def has_agg(e: Any) -> bool:
    return any(isinstance(x, Agg) for x in parts(e))


def bound_inside(e: Any) -> set[str]:
    return {x.name for x in parts(e) if isinstance(x, Each)}


def variables(e: Any) -> set[str]:
    own = bound_inside(e)
    names = {x.name for x in parts(e) if isinstance(x, Var)} | {x.var for x in parts(e) if isinstance(x, (Prop, HasLabels))}
    return names - own


def properties(e: Any) -> set[tuple[str, str]]:
    """(variable, key) pairs that e reads, metadata included."""
    own = bound_inside(e)
    found = {(x.var, x.key) for x in parts(e) if isinstance(x, Prop)}
    found |= {(x.var, LABELS) for x in parts(e) if isinstance(x, HasLabels)}
    return {p for p in found if p[0] not in own}


def replaced(e: Any, swap) -> Any:
    """e with swap(x) in place of every part for which it is not None."""
    if (new := swap(e)) is not None:
        return new
    if not is_dataclass(e) or isinstance(e, Pattern):
        return e
    changed = {}
    for f in fields(e):
        value = getattr(e, f.name)
        if isinstance(value, tuple):
            changed[f.name] = tuple(replaced(x, swap) if is_dataclass(x) else x for x in value)
        elif is_dataclass(value):
            changed[f.name] = replaced(value, swap)
    return type(e)(**{f.name: changed.get(f.name, getattr(e, f.name)) for f in fields(e)})


def conjuncts(e: Any) -> list[Any]:
    return [y for x in e.args for y in conjuncts(x)] if isinstance(e, Op) and e.name == "and" else [e]


def all_of(conditions: list[Any]) -> Any:
    return conditions[0] if len(conditions) == 1 else Op("and", tuple(conditions))


_BINARY = {
    "=": lambda a, b: a == b, "<>": lambda a, b: a != b, "<": lambda a, b: a < b, "<=": lambda a, b: a <= b, ">": lambda a, b: a > b, ">=": lambda a, b: a >= b,
    "+": lambda a, b: a + b, "-": lambda a, b: a - b, "*": lambda a, b: a * b, "/": lambda a, b: a / b, "%": lambda a, b: a % b,
    "starts with": lambda a, b: F.startswith(a, b), "ends with": lambda a, b: F.endswith(a, b), "contains": lambda a, b: F.contains(a, b),
    "xor": lambda a, b: (a & ~b) | (~a & b), "in": lambda a, b: F.array_contains(b, a),
}

#: Functions whose name or shape differs from Spark's.
_CALLS = {
    "head": lambda x: F.get(x, F.lit(0)),
    "last": lambda x: F.element_at(x, -1),
    "length": lambda x: F.size(x),
    "size": lambda x: F.size(x),
    "relationships": lambda x: F.transform(x, lambda s: s["edge"]),
    "nodes": lambda x: F.concat(F.transform(F.slice(x, 1, 1), lambda s: s["src"]), F.transform(x, lambda s: s["trg"])),
    "tolower": lambda x: F.lower(x), "toupper": lambda x: F.upper(x), "tostring": lambda x: x.cast("string"), "tofloat": lambda x: x.cast("double"), "tointeger": lambda x: x.cast("long"),
    "list": lambda *x: F.array(*x),
}


def to_column(e: Any, local: dict[str, Column] | None = None) -> Column:
    """The Spark column of an aggregate-free expression over a flat plan."""
    local = local or {}
    go = lambda x: to_column(x, local)
    match e:
        case Lit(value):
            return F.array(*[F.lit(v) for v in value]) if isinstance(value, (list, tuple)) else F.lit(value)
        case Var(name):
            return local[name] if name in local else column(name)
        case Prop(var, key):
            return local[var][key] if var in local else column(flat(var, key))
        case HasLabels(var, labels):
            return F.size(F.array_except(F.array(*map(F.lit, labels)), column(flat(var, LABELS)))) == 0
        case Op("and", args):
            out = go(args[0])
            for a in args[1:]:
                out = out & go(a)
            return out
        case Op("or", args):
            out = go(args[0])
            for a in args[1:]:
                out = out | go(a)
            return out
        case Op("not", (x,)):
            return ~go(x)
        case Op("neg", (x,)):
            return -go(x)
        case Op("is null", (x,)):
            return go(x).isNull()
        case Op("is not null", (x,)):
            return go(x).isNotNull()
        case Op("index", (x, i)):
            return F.get(go(x), go(i).cast("int"))
        case Op(name, (a, b)):
            return _BINARY[name](go(a), go(b))
        case Each(kind, name, items, body):
            inner = lambda x: to_column(body, {**local, name: x})
            source = go(items)
            return {"all": F.forall, "any": F.exists, "none": lambda c, f: ~F.exists(c, f), "filter": F.filter, "transform": F.transform}[kind](source, inner)
        case Call("field", (x, Lit(key))):
            return go(x)[key]
        case Call(name, args):
            made = [go(a) for a in args]
            return _CALLS[name](*made) if name in _CALLS else F.call_function(name, *made)
    raise PlanError(f"no column for {e}")
