"""Views over edges by nearness that are counted, not joined.

Three near edges that close, or two in a row, of which only properties of the ends and of
few different kinds of the third vertex are asked: a row for each pair of ends and kind, with
the number of vertices between as its weight.  Such a view is cheaper made than kept.
"""

from __future__ import annotations

from dataclasses import dataclass, replace
from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphviews.operators.lowering import Lowering
from graphviews.operators.nearness import near_counts
from graphviews.plans.expr import Agg, Each, HasLabels, Op, Pattern, Prop, Var, all_of, column, conjuncts, flat, parts, properties, replaced, to_column
from graphviews.plans.ops import BOTH, OUT, NaturalJoin, Node, Project, ScanEdges, Select
from graphviews.plans.rewrite import joined_parts
from graphviews.sources.graph import WEIGHT, EdgeSource, PropertyGraph

#: Kinds of the third vertex, at most; types whose equal values a task can tell.
KINDS, PLAIN = 64, ("string", "int", "bigint", "date")


@dataclass(frozen=True)
class NearView:
    """low, high: the ends in the order of keys; third: the vertex that is counted, by its key below, between or above them."""

    node: Project
    source: EdgeSource
    low: str
    high: str
    third: str
    where: str
    reach: int
    same: tuple[str, ...]
    tests: tuple[Any, ...]
    props: tuple[tuple[str, str], ...]

    @property
    def merged(self) -> bool:
        """Whether no two rows are equal: both keys are given, and all that tells kinds apart."""
        given = {(e.var, e.key) for _, e in self.node.items if isinstance(e, Prop)}
        keys = all(any((v, k) in given for k, x in self.props if x == self.source.near.key) for v in (self.low, self.high))
        return keys and {p for p in self._read() if p[0] == self.third} <= given

    def _read(self) -> set[tuple[str, str]]:
        return {p for e in (*self.tests, *(e for _, e in self.node.items)) for p in properties(e)}

    def rows(self, graph: PropertyGraph, old: PropertyGraph | None = None) -> DataFrame | None:
        """The view's weighted rows, or what a change makes of them; None where keys repeat or there are many kinds."""
        if not graph.near_once(self.source) or old is not None and not old.near_once(self.source):
            return None
        read = self._read()
        place = {k: f"x{i}" for i, k in enumerate(sorted({*self.same, *(k for _, k in read)}))}
        key = {k for k, x in self.props if x == self.source.near.key}
        rows = graph.near_rows(self.source, place, old)
        mine = {v: sorted(k for x, k in read if x == v) for v in (self.low, self.high, self.third)}
        few = [place[k] for k in mine[self.third]]
        kinds = rows.select(*few).distinct().limit(KINDS + 1).collect() if few else [()]
        if len(kinds) > KINDS:
            return None
        known = None
        if few:
            schema = ", ".join(["z int", *(f"_{c} {t}" for c, t in rows.select(*few).dtypes)])
            known = F.broadcast(graph.spark.createDataFrame([(i, *r) for i, r in enumerate(kinds)], schema))
            test = [F.col(c).eqNullSafe(F.col(f"_{c}")) for c in few]
            rows = rows.join(known, test, "left").drop(*[f"_{c}" for c in few])
        else:
            rows = rows.withColumn("z", F.lit(0))
        ends = {v: [k for k in mine[v] if k not in key] for v in (self.low, self.high)}
        made = near_counts(rows, self.source.near.width, self.reach, self.where, [place[k] for k in ends[self.low]], [place[k] for k in ends[self.high]], [place[k] for k in self.same], len(kinds))
        kind = dict(rows.dtypes)
        own = [F.col(f"{side}{i}").alias(flat(v, k)) for v, side in ((self.low, "v"), (self.high, "w")) for i, k in enumerate(ends[v])]
        own += [F.col(c).cast(kind[place[k]]).alias(flat(v, k)) for v, c in ((self.low, "k"), (self.high, "k2")) for k in mine[v] if k in key]
        if known is None:
            out = made.select(*own, F.col("sums")[0].alias(WEIGHT))
        else:
            out = made.select(*own, F.posexplode("sums").alias("z", WEIGHT)).where(F.col(WEIGHT) != 0).join(known, "z")
            out = out.select(*[column(c) for c in out.columns if c not in ("z", *(f"_{c}" for c in few))], *[F.col(f"_{place[k]}").alias(flat(self.third, k)) for k in mine[self.third]])
        if self.tests:
            out = out.where(to_column(all_of(list(self.tests))))
        return Lowering(graph).apply(self.node, [out])


def near_view(node: Node, graph: PropertyGraph) -> NearView | None:
    """The way to count a projection over near edges, if it is one."""
    if not isinstance(node, Project) or node.keep:
        return None
    child, tests = node.child, []
    if isinstance(child, Select):
        child, tests = child.child, conjuncts(child.cond)
    edges = joined_parts(child) if isinstance(child, NaturalJoin) else []
    if len(edges) not in (2, 3) or any(not isinstance(p, ScanEdges) or p.direction == BOTH for p in edges) or len({p.e for p in edges}) < len(edges):
        return None
    sources = [graph.near_source(p) for p in edges]
    if None in sources or len({s.type for s in sources}) > 1:
        return None
    name: dict[str, str] = {}
    for c in [c for c in tests if isinstance(c, Op) and c.name == "=" and all(isinstance(a, Var) for a in c.args)]:
        a, b = (name.get(x.name, x.name) for x in c.args)
        name = {x: a if y == b else y for x, y in name.items()} | {b: a}
        tests.remove(c)
    renamed = lambda e: replaced(e, lambda x: replace(x, var=name[x.var]) if isinstance(x, Prop) and x.var in name else None)
    tests = [renamed(c) for c in tests]
    node = replace(node, items=tuple((n, renamed(e)) for n, e in node.items))
    ways = {tuple(name.get(x, x) for x in ((p.v, p.w) if p.direction == OUT else (p.w, p.v))) for p in edges}
    ends = sorted({x for w in ways for x in w}, key=lambda x: -sum(w[0] == x for w in ways))
    if len(ends) != 3 or len(ways) != len(edges):
        return None
    if len(edges) == 2:
        start = [a for a, _ in ways if a not in {b for _, b in ways}]
        if len(start) != 1 or {b for _, b in ways} & {a for a, _ in ways} == set():
            return None
        ends = [start[0], *(b for a, b in ways if a == start[0]), *(b for a, b in ways if a != start[0])]
        allowed = {(ends[0], ends[1]), (ends[1], ends[2])}
    else:
        allowed = {(ends[0], ends[1]), (ends[1], ends[2]), (ends[0], ends[2])}
    asked = [e for e in (*tests, *(e for _, e in node.items))]
    read = {p for e in asked for p in properties(e)}
    bare = any(isinstance(x, (Var, HasLabels, Pattern, Agg, Each)) for e in asked for x in parts(e))
    if ways != allowed or bare or any(v not in ends or k.startswith("@") for v, k in read):
        return None
    source = sources[0]
    props = graph.vertices[source.source].props
    free = [(len([1 for v, _ in read if v == x]), x) for x in ends if not any(v == x and props.get(k) == source.near.key for v, k in read)]
    free = [x for _, x in sorted(free) if len(edges) == 3 or x == ends[1]]
    if not free:
        return None
    third = free[0]
    low, high = (x for x in ends if x != third)
    types = {k: graph.property_type([graph.vertices[source.source]], k) for _, k in read}
    tells = lambda c: isinstance(c, Op) and c.name == "=" and all(isinstance(a, Prop) for a in c.args) and len({a.key for a in c.args}) == 1 and {a.var for a in c.args} == {low, high} and types[c.args[0].key] in PLAIN
    same = tuple(sorted({c.args[0].key for c in tests if tells(c)}))
    rest = tuple(c for c in tests if not tells(c))
    return NearView(node, source, low, high, third, ("below", "between", "above")[ends.index(third)], 1 if len(edges) == 3 else 2, same, rest, tuple(props.items()))
