"""What baselines share: rejection of what a technique cannot do, and its reach."""

from __future__ import annotations

from graphviews.plans.ops import Anti, Distinct, Group, LeftOuter, NaturalJoin, Node, Project, ScanEdges, ScanVertices, Select, Semi, SortTop, TransitiveJoin, Union, Unwind

ALL = {Anti, Distinct, Group, LeftOuter, NaturalJoin, Project, ScanEdges, ScanVertices, Select, Semi, SortTop, TransitiveJoin, Union, Unwind}
BASIC = {NaturalJoin, Project, ScanEdges, ScanVertices, Select, Union}


class Unsupported(ValueError):
    """A plan beyond a technique."""


#: Operators each technique maintains, by name.
REACH = {
    "recompute": ALL,
    "trigger": BASIC,
    "algebraic_set": BASIC | {Distinct},
    "algebraic_bag": BASIC | {Group, Unwind},
    "counting": BASIC | {Distinct},
    "delete_rederive": BASIC | {TransitiveJoin, Distinct},
    "spj": BASIC - {Union},
    "nested": BASIC | {Group, Unwind},
    "closure_sql": BASIC | {TransitiveJoin},
    "summary_delta": BASIC | {Group},
    "outer_delta": BASIC | {LeftOuter, Semi, Anti},
    "value_counts": BASIC | {Group, LeftOuter},
    "order_keys": BASIC | {SortTop, Unwind},
    "topk": BASIC | {SortTop},
    "outer_agg": BASIC | {LeftOuter, Group},
    "higher_order": {NaturalJoin, Project, ScanEdges, ScanVertices, Select, Group},
    "network": ALL,
}

#: Capabilities of the techniques: style, then bag, nested, null, aggregate and order
#: (y full, p partial, n none); fixed values of the literature.
CAPABILITIES = {
    "spj": ("A+P", "n", "n", "n", "n", "n"),
    "algebraic_set": ("A", "n", "n", "n", "n", "n"),
    "counting": ("P", "y", "n", "n", "n", "n"),
    "delete_rederive": ("P", "y", "n", "n", "n", "n"),
    "algebraic_bag": ("A", "y", "n", "n", "p", "n"),
    "nested": ("A", "y", "y", "n", "n", "n"),
    "closure_sql": ("A", "y", "y", "n", "y", "n"),
    "summary_delta": ("P", "y", "n", "n", "y", "n"),
    "outer_delta": ("A", "n", "n", "y", "n", "n"),
    "value_counts": ("P", "y", "n", "y", "y", "n"),
    "order_keys": ("A", "y", "y", "n", "p", "y"),
    "topk": ("P", "n", "n", "n", "n", "n"),
    "outer_agg": ("P", "y", "n", "y", "y", "n"),
    "higher_order": ("A", "y", "n", "p", "p", "p"),
    "network": ("P", "y", "y", "y", "y", "p"),
}


def require(name: str, plan: Node) -> None:
    """Raise Unsupported where a plan has an operator beyond a technique."""
    for node in plan.walk():
        if type(node) not in REACH[name]:
            raise Unsupported(f"{name} does not maintain {type(node).__name__}")
        if name in ("algebraic_bag",) and isinstance(node, Group) and node.keys:
            raise Unsupported("bag equations aggregate without grouping")
        if name == "summary_delta" and isinstance(node, Group) and any(e.name not in ("count", "sum", "avg") or e.distinct for _, e in node.outs):
            raise Unsupported("summary deltas carry counts and sums only")
