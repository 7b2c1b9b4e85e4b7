"""From graph plan to join plan to flat plan."""

from __future__ import annotations

from dataclasses import dataclass, replace
from typing import Any

from graphviews.plans.expr import PlanError, Var, all_of, conjuncts, flat, properties, variables
from graphviews.plans.ops import (
    Anti, Distinct, Dual, Group, LeftOuter, NaturalJoin, Node, Project, ScanEdges, ScanVertices, Select, Semi, SortTop, TransitiveJoin, Union, Unwind, Walk, WalkVar, kinds, rewritten, show,
)


@dataclass(frozen=True)
class Options:
    """Switches for ablations: those that are on are the engine's default."""

    fuse: bool = True
    drop_endpoint: bool = True
    left_deep: bool = True
    cost_based: bool = False


def to_join_plan(plan: Node, options: Options = Options()) -> Node:
    """Walks become joins with edge scans; a scan and the walk from it become one edge scan."""

    def rule(node: Node) -> Node | None:
        match node:
            case Walk(child=c, v=v, e=e, types=types, w=w, labels=labels, direction=d):
                if options.fuse and isinstance(c, ScanVertices) and c.var == v:
                    return ScanEdges(v, c.labels, e, types, w, labels, d)
                return NaturalJoin(c, ScanEdges(v, (), e, types, w, labels, d))
            case WalkVar(child=c, v=v, e=e, types=types, w=w, labels=labels, direction=d, low=low, up=up, mode=mode):
                edges = ScanEdges("_from", (), "_edge", types, "_to", (), d)
                return NaturalJoin(TransitiveJoin(c, edges, v, e, w, low, up, mode, d), ScanVertices(w, labels))
            case NaturalJoin(left=a, right=NaturalJoin(left=b, right=c)) if options.left_deep:
                if set(kinds(a)) & set(kinds(b)):
                    return rewritten(NaturalJoin(NaturalJoin(a, b), c), rule)
        return None

    return rewritten(plan, rule)


def providers(node: Node) -> set[str]:
    """Variables whose properties an operator can hand up."""
    match node:
        case ScanVertices(var=v):
            return {v}
        case ScanEdges(v=v, e=e, w=w):
            return {v, e, w}
        case TransitiveJoin(child=c) | Select(child=c) | Distinct(child=c) | SortTop(child=c) | Unwind(child=c):
            return providers(c)
        case Project(child=c, items=items) | Group(child=c, keys=items):
            inside = providers(c)
            return {n for n, e in items if isinstance(e, Var) and e.name in inside}
        case NaturalJoin(left=a, right=b) | LeftOuter(left=a, right=b):
            return providers(a) | providers(b)
        case Semi(left=a) | Anti(left=a) | Union(left=a):
            return providers(a)
    return set()


def infer_required(node: Node, need: frozenset = frozenset()) -> Node:
    """Push the properties that each operator and those above it read down to the leaves."""
    match node:
        case Dual():
            return node
        case ScanVertices(var=v):
            return replace(node, props=tuple(sorted(k for x, k in need if x == v)))
        case ScanEdges(v=v, e=e, w=w):
            return replace(node, props=tuple(sorted(p for p in need if p[0] in (v, e, w))))
        case TransitiveJoin(child=c, edges=edges):
            return replace(node, child=infer_required(c, need), edges=infer_required(edges))
        case Select(child=c, cond=cond):
            return replace(node, child=infer_required(c, need | properties(cond)))
        case Unwind(child=c, items=items):
            return replace(node, child=infer_required(c, need | properties(items)))
        case SortTop(child=c, keys=keys):
            own = {p for e, _ in keys for p in properties(e)}
            return replace(node, child=infer_required(c, need | own))
        case Distinct(child=c):
            return replace(node, child=infer_required(c, need))
        case Project(child=c, items=items):
            below, keep = _through(items, need)
            return replace(node, child=infer_required(c, frozenset(below)), keep=keep)
        case Group(child=c, keys=keys, outs=outs):
            below, keep = _through(keys, need)
            below |= {p for _, e in outs for p in properties(e)}
            return replace(node, child=infer_required(c, frozenset(below)), keep=keep)
        case NaturalJoin(left=a, right=b) | LeftOuter(left=a, right=b):
            if isinstance(node, LeftOuter) and node.cond is not None:
                need = need | properties(node.cond)
            mine, theirs = providers(a), providers(b)
            for x, k in need:
                if x not in mine | theirs:
                    raise PlanError(f"{x} has no properties to read ({k})")
            return replace(node, left=infer_required(a, frozenset(p for p in need if p[0] in mine)), right=infer_required(b, frozenset(p for p in need if p[0] not in mine)))
        case Semi(left=a, right=b) | Anti(left=a, right=b):
            return replace(node, left=infer_required(a, need), right=infer_required(b))
        case Union(left=a, right=b):
            return replace(node, left=infer_required(a, need), right=infer_required(b, need))
    raise TypeError(node)


def _through(items, need: frozenset) -> tuple[set, tuple]:
    """What a projection or grouping needs below it, and the properties it carries along with variables."""
    alias = {n: e.name for n, e in items if isinstance(e, Var)}
    keep = tuple(sorted(p for p in need if p[0] in alias))
    below = {(alias[n], k) for n, k in keep} | {p for _, e in items for p in properties(e)}
    return below, keep


def drop_endpoint_joins(plan: Node, graph: Any) -> Node:
    """Remove vertex joins behind transitive joins that neither test a label nor bring a property."""

    def rule(node: Node) -> Node | None:
        match node:
            case NaturalJoin(left=TransitiveJoin() as t, right=ScanVertices(labels=labels, props=())):
                if not labels or (t.low >= 1 or _has_labels(t.child, t.v, labels)) and graph.ends_have_labels(t.edges.types, t.direction, labels):
                    return t
        return None

    return rewritten(plan, rule)


def _has_labels(node: Node, var: str, labels: tuple[str, ...]) -> bool:
    for n in node.walk():
        match n:
            case ScanVertices(var=v, labels=own) if v == var and set(labels) <= set(own):
                return True
            case ScanEdges(v=v, v_labels=a, w=w, w_labels=b):
                if (v == var and set(labels) <= set(a)) or (w == var and set(labels) <= set(b)):
                    return True
    return False


def flat_columns(node: Node) -> list[str]:
    """Columns of a flat plan's operator: variables, then the properties it carries."""
    match node:
        case Dual():
            return []
        case ScanVertices(var=v, props=props):
            return [v, *(flat(v, k) for k in props)]
        case ScanEdges(v=v, e=e, w=w, props=props):
            return [v, e, w, *(flat(*p) for p in props)]
        case TransitiveJoin(child=c, e=e, w=w):
            return [*flat_columns(c), e, w]
        case Project(items=items, keep=keep):
            return [*(n for n, _ in items), *(flat(*p) for p in keep)]
        case Group(keys=keys, outs=outs, keep=keep):
            return [*(n for n, _ in keys), *(n for n, _ in outs), *(flat(*p) for p in keep)]
        case Unwind(child=c, name=n, place=p):
            return [*flat_columns(c), n, *([p] if p else [])]
        case NaturalJoin(left=a, right=b) | LeftOuter(left=a, right=b):
            left = flat_columns(a)
            return [*left, *(x for x in flat_columns(b) if x not in left)]
        case Semi(left=a) | Anti(left=a) | Union(left=a):
            return flat_columns(a)
        case Select(child=c) | Distinct(child=c) | SortTop(child=c):
            return flat_columns(c)
    raise TypeError(node)


def pushed(node: Node) -> Node:
    """Selections as deep as they go: into the inputs of joins and below transitive joins, which are no single plan for Spark."""
    node = node.with_children([pushed(c) for c in node.children()])
    if not isinstance(node, Select):
        return node
    out, kept = node.child, []
    for c in conjuncts(node.cond):
        lower = _sunk(out, c)
        if lower is None:
            kept.append(c)
        else:
            out = lower
    return Select(out, all_of(kept)) if kept else out


def _sunk(node: Node, cond: Any) -> Node | None:
    """The operator with a condition below it, where it can go there."""
    own = {v for v, _ in properties(cond)}

    def fits(side: Node, others: set[str] = frozenset()) -> bool:
        return variables(cond) <= set(kinds(side)) and own <= providers(side) - others

    def below(side: Node) -> Node:
        return _sunk(side, cond) or Select(side, cond)

    match node:
        case Select(child=c):
            lower = _sunk(c, cond)
            return None if lower is None else replace(node, child=lower)
        case NaturalJoin(left=a, right=b):
            if fits(a):
                return replace(node, left=below(a))
            return replace(node, right=below(b)) if fits(b, providers(a)) else None
        case TransitiveJoin(child=c):
            return replace(node, child=below(c)) if fits(c) else None
        case LeftOuter(left=a) | Semi(left=a) | Anti(left=a):
            return replace(node, left=below(a)) if fits(a) else None
    return None


def seeking_ends(plan: Node) -> Node:
    """Transitive joins whose ends are selected walk back from those."""

    def rule(node: Node) -> Node | None:
        match node:
            case NaturalJoin(left=TransitiveJoin(ends=None) as t, right=Select() as ends) if isinstance(_scan_under(ends), ScanVertices) and _scan_under(ends).var == t.w:
                return replace(node, left=replace(t, ends=ends))
        return None

    return rewritten(plan, rule)


def _scan_under(node: Node) -> Node:
    return _scan_under(node.child) if isinstance(node, Select) else node


def joined_parts(node: Node) -> list[Node]:
    """The inputs of a tree of natural joins, from left to right."""
    return [*joined_parts(node.left), *joined_parts(node.right)] if isinstance(node, NaturalJoin) else [node]


def connected(parts: list, names, first: int = 0, cost=None) -> list[int]:
    """An order of parts from the first one, each next to one before it; names gives a part's variables, cost what to take first."""
    order, left = [first], [i for i in range(len(parts)) if i != first]
    have = set(names(parts[first]))
    while left:
        near = [i for i in left if have & set(names(parts[i]))] or left
        best = min(near, key=lambda i: (cost(parts[i]) if cost else 0, i))
        order.append(best)
        left.remove(best)
        have |= set(names(parts[best]))
    return order


def cost_ordered(plan: Node, graph: Any) -> Node:
    """Joins of three and more inputs start with the smallest one by its estimate and go on with the smallest that is connected.

    Estimates are bytes of the tables behind a leaf, a tenth of it for each selection that stands on it.
    """

    def cost(node: Node) -> float:
        match node:
            case Select(child=c):
                return cost(c) / 10
            case ScanVertices() | ScanEdges():
                return graph.estimate(node)
            case Dual():
                return 0.0
        return sum(map(cost, node.children()))

    def over(node: Node) -> Node:
        if isinstance(node, NaturalJoin):
            parts = [over(p) for p in joined_parts(node)]
            if len(parts) > 2:
                order = connected(parts, kinds, min(range(len(parts)), key=lambda i: (cost(parts[i]), i)), cost)
                parts = [parts[i] for i in order]
            out = parts[0]
            for p in parts[1:]:
                out = NaturalJoin(out, p)
            return out
        return node.with_children([over(c) for c in node.children()])

    return over(plan)


@dataclass(frozen=True)
class Plans:
    """The three plans of a query."""

    graph: Node
    join: Node
    flat: Node

    def explain(self) -> str:
        return "\n".join(f"== {n} plan ==\n{show(getattr(self, n))}" for n in ("graph", "join", "flat"))


def compiled(plan: Node, graph: Any, options: Options = Options()) -> Plans:
    """All three plans; graph tells which labels edge ends are known to have."""
    join = to_join_plan(plan, options)
    flat_plan = infer_required(join)
    if options.drop_endpoint:
        flat_plan = drop_endpoint_joins(flat_plan, graph)
    if options.cost_based:
        flat_plan = cost_ordered(flat_plan, graph)
    return Plans(plan, join, flat_plan)


def join_count(node: Node) -> int:
    return sum(isinstance(n, (NaturalJoin, LeftOuter, Semi, Anti, TransitiveJoin)) for n in node.walk())
