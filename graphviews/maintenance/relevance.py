"""Changes that cannot matter to a view, found before anything is propagated."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphviews.maintenance.changes import ChangeSet
from graphviews.plans.expr import Lit, Op, Prop, conjuncts, properties, to_column
from graphviews.plans.ops import NaturalJoin, Node, ScanEdges, ScanVertices, Select
from graphviews.sources.graph import PropertyGraph, inputs_of


def leaf_conditions(plan: Node, own: tuple = ()) -> list[tuple[Node, tuple]]:
    """Leaves with the conditions that every row of theirs must meet to matter.

    Those are conjuncts over one variable's properties and constants, of selections with
    nothing but joins and other selections between them and the leaf.
    """
    if isinstance(plan, Select):
        mine = [c for c in conjuncts(plan.cond) if isinstance(c, Op) and all(isinstance(a, (Prop, Lit)) for a in c.args) and len({v for v, _ in properties(c)}) == 1]
        return leaf_conditions(plan.child, (*own, *mine))
    if isinstance(plan, NaturalJoin):
        return [*leaf_conditions(plan.left, own), *leaf_conditions(plan.right, own)]
    if isinstance(plan, (ScanVertices, ScanEdges)):
        return [(plan, own)]
    return [found for c in plan.children() for found in leaf_conditions(c)]


def relevant(plan: Node, graph: PropertyGraph, changes: ChangeSet) -> ChangeSet:
    """The change set without rows that no leaf of a view would let through.

    A row stays where any leaf over its table has no constant condition on it, or one
    it meets; tables that derived sources read are left whole.
    """
    tests: dict[str, list] = {}
    whole: set[str] = set()
    for leaf, conditions in leaf_conditions(plan):
        if isinstance(leaf, ScanVertices):
            pairs = [(s, leaf.var) for s in graph.vertices.values() if graph.may_have(s, leaf.labels)]
        else:
            pairs = [(s, leaf.e) for s in graph.edge_sources(leaf.types)]
            if leaf.ends:
                ends = {x for s, _ in pairs for x in (s.source, s.target)}
                pairs += [(graph.vertices[x], v) for x in ends for v in (leaf.v, leaf.w)]
        for source, var in pairs:
            if source.derive is not None:
                whole |= inputs_of(source)
                continue
            own = [c for c in conditions if all(v == var and k in source.props for v, k in properties(c))]
            tests.setdefault(source.table, []).append((source, var, own))
    out: dict[str, DataFrame] = {}
    for table, df in changes.tables.items():
        if table in whole:
            out[table] = df
            continue
        if table not in tests:
            continue  # no leaf reads it
        keep = F.lit(False)
        for source, var, own in tests[table]:
            cond = F.lit(True) if source.where is None else F.expr(source.where)
            if own:
                named = {f"{var}__{k}": F.expr(source.props[k]) for c in own for _, k in properties(c)}
                cond = cond & _substituted(own, named)
            keep = keep | F.coalesce(cond, F.lit(False))
        out[table] = df.where(keep)
    return ChangeSet(out)


def _substituted(conditions: list, named: dict):
    """Conditions over a source's own columns."""
    local = {v: _Row(named, v) for c in conditions for v, _ in properties(c)}
    result = None
    for c in conditions:
        made = to_column(c, local)
        result = made if result is None else result & made
    return result


class _Row:
    """Looks a property up as the source's expression for it."""

    def __init__(self, named: dict, var: str):
        self.named, self.var = named, var

    def __getitem__(self, key: str):
        return self.named[f"{self.var}__{key}"]


def affected_views(views: dict, changes: ChangeSet) -> list[str]:
    """Impact analysis: names of views that some row of the change may touch."""
    out = []
    for name, view in views.items():
        left = relevant(view.plans.flat, view.network.graph, changes)
        if any(df.limit(1).count() for df in left.tables.values()):
            out.append(name)
    return out
