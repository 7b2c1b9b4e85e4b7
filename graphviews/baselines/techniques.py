"""Maintenance techniques to compare with the network, over (old graph, change set)."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphviews.baselines.common import Unsupported, require
from graphviews.maintenance.changes import ChangeSet, added, negated, weighted
from graphviews.maintenance.network import Network, primitive_leaves
from graphviews.maintenance.relevance import relevant
from graphviews.maintenance.states import TopState
from graphviews.operators.lowering import Lowering, shared_variables
from graphviews.operators.ordering import between, numbered
from graphviews.operators.paths import expand
from graphviews.plans.expr import column, to_column
from graphviews.plans.ops import Anti, Distinct, Group, LeftOuter, NaturalJoin, Node, Project, ScanEdges, ScanVertices, Select, Semi, SortTop, Union, Unwind
from graphviews.sources.graph import WEIGHT, PropertyGraph, consolidated, weighted_join
from graphviews.sources.shared import run_of, stored


def rows_of(bag: DataFrame) -> DataFrame:
    bag = consolidated(bag, positive=True)
    return bag.withColumn("_n", F.explode(F.sequence(F.lit(1).cast("long"), F.col(WEIGHT)))).drop("_n", WEIGHT)


def changed(graph: PropertyGraph, changes: ChangeSet) -> PropertyGraph:
    old = graph.with_tables({t: weighted(df) for t, df in graph.tables.items()})
    return old.with_tables({t: added([old.tables[t], d.select(*old.tables[t].columns)]) for t, d in changes.tables.items()})


def recompute(plan: Node, graph: PropertyGraph, changes: ChangeSet) -> DataFrame:
    """One-time evaluation on the changed tables."""
    return rows_of(Lowering(changed(graph, changes)).df(plan))


class DeltaQueries:
    """The change of a plan's bag as queries over old and new tables and their changes.

    Nothing is kept between refreshes but the tables; sub-plans are evaluated where
    the derived queries mention them.
    """

    def __init__(self, graph: PropertyGraph, changes: ChangeSet):
        self.old = graph.with_tables({t: weighted(df) for t, df in graph.tables.items()})
        self.new = changed(graph, changes)
        self.net = Network(graph, ScanVertices("_none"), state="none")
        self.net.old, self.net.new = self.old, self.new
        self.net.delta_tables = {t: consolidated(d.select(*self.old.tables[t].columns)) for t, d in changes.tables.items()}

    def delta(self, node: Node) -> DataFrame | None:
        if isinstance(node, (ScanVertices, ScanEdges)):
            return self.net.leaf_delta(node)
        below = [self.delta(c) for c in node.children()]
        if all(d is None for d in below):
            return None
        if isinstance(node, NaturalJoin):
            return self.joined(node, *below)
        if isinstance(node, (Select, Project, Unwind, Union)):
            return added(below) if isinstance(node, Union) else Lowering(self.new).apply(node, below)
        return self.other(node, *below)

    def joined(self, node: Node, left: DataFrame | None, right: DataFrame | None) -> DataFrame:
        """Each side's change with the other side: new for the left change, old for the right one."""
        on = shared_variables(node.left, node.right)
        parts = []
        if left is not None:
            parts.append(weighted_join(left, Lowering(self.new).df(node.right), on))
        if right is not None:
            parts.append(weighted_join(Lowering(self.old).df(node.left), right, on))
        return added([p.select(*[column(c) for c in parts[0].columns]) for p in parts])

    def other(self, node: Node, *below) -> DataFrame:
        raise Unsupported(f"no change equation for {type(node).__name__}")


class OuterEquations(DeltaQueries):
    """Change equations of semi, anti and outer joins besides.

    An outer join is the join, and the left rows without a match filled up with nulls.
    Left rows change theirs by themselves; a change of the right side moves those left
    rows that it meets and that had no match before, or have none after.
    """

    def other(self, node: Node, left: DataFrame | None, right: DataFrame | None) -> DataFrame:
        if not isinstance(node, (LeftOuter, Semi, Anti)):
            return super().other(node, left, right)
        on = shared_variables(node.left, node.right)
        old_left, old_right, new_right = Lowering(self.old).df(node.left), Lowering(self.old).df(node.right), Lowering(self.new).df(node.right)
        cond = node.cond if isinstance(node, LeftOuter) else None
        alone = []
        if left is not None:
            alone.append(self.met(left, new_right, on, cond, "left_anti"))
        if right is not None:
            moved = consolidated(self.met(old_left, right, on, cond, "left_semi"))
            lost = self.met(self.met(moved, old_right, on, cond, "left_semi"), new_right, on, cond, "left_anti")
            found = self.met(self.met(moved, new_right, on, cond, "left_semi"), old_right, on, cond, "left_anti")
            alone += [lost, negated(found)]
        if isinstance(node, Anti):
            return added(alone)
        if isinstance(node, Semi):
            # what a semi join has, an anti join has not
            return added([*([left] if left is not None else []), *map(negated, alone)])
        joined = self.joined(node, left, right)
        both = joined if cond is None else joined.where(to_column(cond))
        names = both.columns
        filled = [a.select(*[column(c) if c in a.columns else F.lit(None).cast(both.schema[c].dataType).alias(c) for c in names]) for a in alone]
        return added([both, *filled])

    @staticmethod
    def met(rows: DataFrame, others: DataFrame, on: list[str], cond, how: str) -> DataFrame:
        """Rows with (or without) a match among others of positive weight, or of any weight in a change."""
        there = consolidated(others)
        there = there.drop(WEIGHT, *[c for c in there.columns if c in rows.columns and c not in on]).withColumnsRenamed({c: f"_right_{c}" for c in on})
        tests = [column(c) == column(f"_right_{c}") for c in on] + ([to_column(cond)] if cond is not None else [])
        return rows.join(there, reduce(lambda a, b: a & b, tests) if tests else F.lit(True), how)


class SetEquations:
    """Insertions and deletions of a plan under set semantics, two queries for every operator.

    A projection or union can derive a row twice: what is deleted must have no other
    derivation in the new state, and what is inserted none in the old one.
    """

    def __init__(self, graph: PropertyGraph, changes: ChangeSet):
        self.bags = DeltaQueries(graph, changes)

    def state(self, node: Node, fresh: bool) -> DataFrame:
        return consolidated(Lowering(self.bags.new if fresh else self.bags.old).df(node), positive=True).drop(WEIGHT)

    @staticmethod
    def less(a: DataFrame, b: DataFrame) -> DataFrame:
        return a.select(*b.columns).exceptAll(b) if a is b else a.select(*[column(c) for c in b.columns]).subtract(b)

    def change(self, node: Node) -> tuple[DataFrame, DataFrame] | None:
        """(insertions, deletions), both sets; None where there are none."""
        if isinstance(node, (ScanVertices, ScanEdges)):
            delta = self.bags.net.leaf_delta(node)
            if delta is None:
                return None
            delta = consolidated(delta)
            come, go = (delta.where(F.col(WEIGHT) * sign > 0).drop(WEIGHT) for sign in (1, -1))
            return self.less(come, self.state(node, False)), self.less(go, self.state(node, True))
        below = [self.change(c) for c in node.children()]
        if all(b is None for b in below):
            return None
        if isinstance(node, Select):
            return tuple(x.where(to_column(node.cond)) for x in below[0])
        if isinstance(node, NaturalJoin):
            on = shared_variables(node.left, node.right)
            sides = []
            for k, fresh in ((0, True), (1, False)):
                left, right = self.state(node.left, fresh), self.state(node.right, fresh)
                parts = [weighted_join(below[0][k], right, on)] if below[0] else []
                parts += [weighted_join(left, below[1][k], on)] if below[1] else []
                sides.append(added([p.select(*[column(c) for c in parts[0].columns]) for p in parts]).distinct())
            return sides[0], sides[1]
        if isinstance(node, (Project, Distinct, Union)):
            shape = (lambda x: Lowering(self.bags.new).apply(node, [x])) if isinstance(node, Project) else (lambda x: x)
            come, go = (added([shape(b[k]) for b in below if b]).distinct() for k in (0, 1))
            return self.less(come, self.state(node, False)), self.less(go, self.state(node, True))
        raise Unsupported(f"no set equation for {type(node).__name__}")


def algebraic(plan: Node, graph: PropertyGraph, changes: ChangeSet, semantics: str = "bag") -> DataFrame:
    """The view from change equations: old less deletions, plus insertions."""
    require(f"algebraic_{semantics}", plan)
    plan = primitive_leaves(plan, graph)
    if semantics == "set":
        derived = SetEquations(graph, changes)
        old, change = derived.state(plan, False), derived.change(plan)
        return old if change is None else derived.less(old, change[1]).union(change[0].select(*[column(c) for c in old.columns]))
    over, group = [], plan
    while isinstance(group, Project):
        over, group = [group, *over], group.child
    if isinstance(group, Group):
        return _aggregated(group, over, DeltaQueries(graph, changes))
    derived = DeltaQueries(graph, changes)
    old = consolidated(Lowering(derived.old).df(plan))
    delta = derived.delta(plan)
    return rows_of(old if delta is None else added([old, delta]))


def _aggregated(group: Group, over: list[Node], derived: DeltaQueries) -> DataFrame:
    """A count or sum of everything: the old value and what the change adds up to."""
    for _, a in group.outs:
        if a.name not in ("count", "sum") or a.distinct:
            raise Unsupported("bag equations add up counts and sums only")
    old = Lowering(derived.old).df(group)
    delta = derived.delta(group.child)
    if delta is not None:
        more = [F.sum((to_column(a.arg) if a.name == "sum" else F.lit(1) if a.arg is None else F.when(to_column(a.arg).isNotNull(), 1)) * F.col(WEIGHT)).alias(f"_d{i}") for i, (_, a) in enumerate(group.outs)]
        both = old.drop(WEIGHT).crossJoin(delta.agg(*more))  # one row each
        old = both.select(*[(F.coalesce(column(n), F.lit(0)) + F.coalesce(F.col(f"_d{i}"), F.lit(0))).alias(n) for i, (n, _) in enumerate(group.outs)])
    else:
        old = old.drop(WEIGHT)
    for node in over:
        old = Lowering(derived.new).apply(node, [old])
    return old


def trigger(plan: Node, graph: PropertyGraph, changes: ChangeSet) -> DataFrame:
    """One statement after the other: each changed table fires a query that puts its change into the stored view, the other tables as they are then."""
    require("trigger", plan)
    plan = primitive_leaves(plan, graph)
    now = graph.with_tables({t: weighted(df) for t, df in graph.tables.items()})
    view = stored(consolidated(Lowering(now).df(plan)), "triggered")
    for table, rows in changes.tables.items():
        one = ChangeSet({table: rows})
        delta = DeltaQueries(now, one).delta(plan)
        if delta is not None:
            view = stored(consolidated(added([view, delta.select(*[column(c) for c in view.columns])])), "triggered")
        now = changed(now, one)
    return rows_of(view)


def counting(plan: Node, graph: PropertyGraph, changes: ChangeSet) -> DataFrame:
    """Each tuple with its number of derivations; a tuple goes when the number is zero."""
    require("counting", plan)
    body = plan.child if isinstance(plan, Distinct) else plan
    body = primitive_leaves(body, graph)
    derived = DeltaQueries(graph, changes)
    counts = stored(consolidated(Lowering(derived.old).df(body)), "counts")
    delta = derived.delta(body)
    bag = counts if delta is None else added([counts, delta])
    return consolidated(bag, positive=True).drop(WEIGHT) if isinstance(plan, Distinct) else rows_of(bag)


def spj(plan: Node, graph: PropertyGraph, changes: ChangeSet) -> tuple[DataFrame, dict[str, int]]:
    """Select-project-join views; changes that no leaf's conditions can meet are dropped first."""
    require("spj", plan)
    changes = relevant(plan, graph, changes)
    plan = primitive_leaves(plan, graph)
    derived = DeltaQueries(graph, changes)
    kept = {}
    for node in plan.walk():
        if isinstance(node, (ScanVertices, ScanEdges)):
            delta = derived.net.leaf_delta(node)
            kept[str(node)[:60]] = 0 if delta is None else consolidated(delta).count()
    delta = derived.delta(plan)
    old = Lowering(derived.old).df(plan)
    return rows_of(old if delta is None else added([old, delta])), kept


def outer_delta(plan: Node, graph: PropertyGraph, changes: ChangeSet) -> DataFrame:
    """Semi, anti and outer join views from their change equations."""
    require("outer_delta", plan)
    plan = primitive_leaves(plan, graph)
    derived = OuterEquations(graph, changes)
    old = consolidated(Lowering(derived.old).df(plan))
    delta = derived.delta(plan)
    return rows_of(old if delta is None else added([old, delta.select(*[column(c) for c in old.columns])]))


def outer_agg(plan: Node, graph: PropertyGraph, changes: ChangeSet) -> DataFrame:
    """Groupings over outer joins: the change of the outer join, summed by group, merged into the view's sums."""
    return summary_delta(plan, graph, changes, "outer_agg", OuterEquations)


def summary_delta(plan: Node, graph: PropertyGraph, changes: ChangeSet, technique: str = "summary_delta", equations: type = DeltaQueries) -> DataFrame:
    """A grouped view from its change summed by group first, then merged into the view's sums."""
    require(technique, plan)
    after = [] if isinstance(plan, Group) else [plan]
    group = plan if isinstance(plan, Group) else plan.child
    if not isinstance(group, Group):
        raise Unsupported("summary deltas are of grouped views")
    if any(e.name not in ("count", "sum", "avg") or e.distinct for _, e in group.outs):
        raise Unsupported("summary deltas carry counts and sums only")
    child = primitive_leaves(group.child, graph)
    derived = equations(graph, changes)

    def sums(bag: DataFrame) -> DataFrame:
        keys = [to_column(e).alias(n) for n, e in group.keys]
        own = [F.sum(WEIGHT).alias("_rows")]
        for n, e in group.outs:
            x = to_column(e.arg) if e.arg is not None else F.lit(1)
            own.append(F.sum(F.when(x.isNotNull(), F.col(WEIGHT)).otherwise(0)).alias(f"_n_{n}"))
            own.append((F.sum((x * F.col(WEIGHT)).cast("decimal(38,6)")) if e.name != "count" else F.sum(F.lit(0))).cast("decimal(38,6)").alias(f"_s_{n}"))
        return bag.groupBy(*keys).agg(*own)

    old = stored(sums(Lowering(derived.old).df(child)), "sums")
    delta = derived.delta(child)
    both = old if delta is None else old.unionByName(sums(delta))
    names = [c for c in old.columns if c.startswith("_")]
    total = both.groupBy(*[n for n, _ in group.keys]).agg(*[F.sum(c).alias(c) for c in names]).where("_rows > 0")
    made = []
    for n, e in group.outs:
        value = {"count": F.col(f"_n_{n}").cast("long"), "sum": F.when(F.col(f"_n_{n}") > 0, F.col(f"_s_{n}").cast("double")), "avg": F.col(f"_s_{n}").cast("double") / F.col(f"_n_{n}")}[e.name]
        made.append(value.alias(n))
    out = total.select(*[n for n, _ in group.keys], *made)
    for node in after:
        out = Lowering(derived.new.with_tables({})).apply(node, [out])
    return out


def value_counts(plan: Node, graph: PropertyGraph, changes: ChangeSet) -> DataFrame:
    """Minima and maxima from counts of values: a deleted extremum is followed by the next value that is left."""
    require("value_counts", plan)
    group = plan if isinstance(plan, Group) else plan.child
    child = primitive_leaves(group.child, graph)
    derived = DeltaQueries(graph, changes)
    keys = [to_column(e).alias(n) for n, e in group.keys]
    args = [to_column(e.arg).alias(f"_x_{n}") for n, e in group.outs]

    def counts(bag: DataFrame) -> DataFrame:
        return consolidated(bag.select(*keys, *args, WEIGHT))

    old = stored(counts(Lowering(derived.old).df(child)), "values")
    delta = derived.delta(child)
    left = consolidated(old if delta is None else old.unionByName(counts(delta)), positive=True)
    return left.groupBy(*[n for n, _ in group.keys]).agg(*[getattr(F, e.name)(f"_x_{n}").alias(n) for n, e in group.outs])


def delete_rederive(old_edges: DataFrame, inserted: DataFrame, deleted: DataFrame) -> DataFrame:
    """Reachable pairs (s, t) after edges (s, t, e) come and go: drop what used a deleted edge, derive again, then extend."""
    reach = lambda edges, seeds: expand(seeds, edges, 1, None, "reach").select(F.col("start").alias("s"), F.col("end").alias("t"))
    seeds = old_edges.select(F.col("s").alias("start")).distinct()
    pairs = stored(reach(old_edges, seeds), "pairs")
    kept_edges = stored(old_edges.join(deleted.select("e"), "e", "left_anti").select("s", "t").distinct(), "kept")
    back = old_edges.select(F.col("t").alias("s"), F.col("s").alias("t"), "e")
    before = expand(deleted.select(F.col("s").alias("start")).distinct(), back, 0, None, "reach").select(F.col("start").alias("x"), F.col("end").alias("s"))
    after = expand(deleted.select(F.col("t").alias("start")).distinct(), old_edges, 0, None, "reach").select(F.col("start").alias("y"), F.col("end").alias("t"))
    over = deleted.select(F.col("s").alias("x"), F.col("t").alias("y")).distinct().join(before, "x").join(after, "y").select("s", "t").distinct()
    # whoever may have used a deleted edge is gone, until an edge that is left derives it from a pair that survives
    gone = stored(pairs.join(over, ["s", "t"]), "gone")
    alive = [stored(pairs.join(over, ["s", "t"], "left_anti"), "sure")]
    step = stored(gone.join(kept_edges, ["s", "t"]), "again")
    found = alive[0]
    while True:
        through = kept_edges.withColumnRenamed("t", "m").join(found.withColumnRenamed("s", "m"), "m").select("s", "t")
        step = run_of(step.unionByName(gone.join(through, ["s", "t"], "left_semi")).distinct().join(reduce(DataFrame.unionByName, alive), ["s", "t"], "left_anti"), "again")
        if not step.rows:
            break
        alive.append(step.df)
        found, step = step.df, step.df.limit(0)
    # insertions: new pairs go on by one edge at either end, until nothing is new
    edges = stored(kept_edges.unionByName(inserted.select("s", "t")).distinct(), "edges")
    step = inserted.select("s", "t").distinct()
    while True:
        step = run_of(step.join(reduce(DataFrame.unionByName, alive), ["s", "t"], "left_anti"), "more")
        if not step.rows:
            return reduce(DataFrame.unionByName, alive)
        alive.append(step.df)
        ahead = step.df.withColumnRenamed("t", "m").join(edges.withColumnRenamed("s", "m"), "m").select("s", "t")
        behind = edges.withColumnRenamed("t", "m").join(step.df.withColumnRenamed("s", "m"), "m").select("s", "t")
        step = ahead.unionByName(behind).distinct()


def _reaching(edges: DataFrame, all_edges: DataFrame) -> DataFrame:
    back = all_edges.select(F.col("t").alias("s"), F.col("s").alias("t"), "e")
    return expand(edges.select(F.col("s").alias("start")).distinct(), back, 0, None, "reach").select(F.col("end").alias("start"))


def path_counts(edges: DataFrame, seeds: DataFrame) -> DataFrame:
    """(s, t, n): how many paths lead from each seed (start) to each vertex of an acyclic graph; counts are added up hop by hop, no path is made."""
    step = edges.join(seeds.select(F.col("start").alias("s")).distinct(), "s").groupBy("s", "t").agg(F.count(F.lit(1)).alias("n"))
    onward = stored(edges.groupBy(F.col("s").alias("by"), F.col("t").alias("u")).agg(F.count(F.lit(1)).alias("m")).withColumnRenamed("by", "t"), "onward")
    levels = []
    while True:
        run = run_of(step, "paths")
        if not run.rows:
            break
        levels.append(run.df)
        step = run.df.join(onward, "t").groupBy("s", F.col("u").alias("t")).agg(F.sum(F.col("n") * F.col("m")).alias("n"))
    return reduce(DataFrame.unionByName, levels).groupBy("s", "t").agg(F.sum("n").alias("n")) if levels else run.df


def closure_counts(old_edges: DataFrame, inserted: DataFrame, deleted: DataFrame) -> DataFrame:
    """Reachable pairs of an acyclic graph with their numbers of paths; only sources that reach a changed edge count anew."""
    old = stored(path_counts(old_edges, old_edges.select(F.col("s").alias("start"))), "counted")
    new_edges = old_edges.join(deleted.select("e"), "e", "left_anti").unionByName(inserted)
    touched = _reaching(deleted, old_edges).unionByName(_reaching(inserted, new_edges)).distinct()
    less = old.join(touched.select(F.col("start").alias("s")), "s", "left_semi").withColumn("n", -F.col("n"))
    more = path_counts(new_edges, touched)
    return reduce(DataFrame.unionByName, [old, less, more]).groupBy("s", "t").agg(F.sum("n").alias("n")).where("n > 0")


def order_keys(old: DataFrame, inserted: DataFrame, deleted: DataFrame, by: list) -> DataFrame:
    """A sorted view whose rows carry order keys: new rows get keys between their neighbours', old keys stay.

    Where a gap has no room for another key, all rows are numbered anew.
    """
    from pyspark.sql import Window

    keyed = old if "_pos" in old.columns else stored(numbered(old, by, "_pos").withColumn("_pos", F.col("_pos").cast("double")), "ordered")
    names = [c for c in keyed.columns if c != "_pos"]
    left = keyed.join(deleted.select(*names), names, "left_anti").withColumn("_new", F.lit(False))
    both = between(left.unionByName(inserted.select(*names).withColumns({"_pos": F.lit(None).cast("double"), "_new": F.lit(True)})), by, "_pos")
    gap = Window.partitionBy("_low", "_high")
    low, high = F.coalesce("_low", F.col("_high") - 1, F.lit(0.0)), F.coalesce("_high", F.col("_low") + 1, F.lit(1.0))
    # old rows stand between their own key and itself, so they are gaps of one row
    key = F.when(F.col("_new"), low + (high - low) * F.row_number().over(gap.orderBy(*by)) / (F.count(F.lit(1)).over(gap) + 1)).otherwise(F.col("_pos"))
    made = run_of(both.withColumn("_pos", key).drop("_low", "_high", "_new"), "ordered")
    if made.df.select("_pos").distinct().count() < made.rows:
        return numbered(made.df.drop("_pos"), by, "_pos").withColumn("_pos", F.col("_pos").cast("double"))
    return made.df


def topk(plan: SortTop, graph: PropertyGraph, changes: ChangeSet, spare: int = 50) -> tuple[DataFrame, bool]:
    """The k best rows, kept with spare ones: deletes eat the spare rows, and only when they are used up the view is computed anew."""
    if plan.skip or plan.limit is None:
        raise Unsupported("a top-k view has a limit and no skip")
    child = primitive_leaves(plan.child, graph)
    derived = DeltaQueries(graph, changes)
    state = TopState(plan, "topk", spare=spare)
    state.load(Lowering(derived.old).df(child))
    delta = derived.delta(child)
    if delta is not None:
        state.refresh(delta, lambda: Lowering(derived.new).df(child))
    return rows_of(state.relation(True)), state.refills > 0


def higher_order(graph: PropertyGraph, changes: ChangeSet) -> DataFrame:
    """Revenue by customer segment and part brand, where the change queries are kept as tables themselves.

    For a changed line the join needs the segment of its order and the brand of its part;
    for a changed order its lines; for a changed customer the sums of the lines by customer
    and part; for a changed part the sums by part and segment.  These are kept.  A change
    of one table meets the new state of the tables after it and the old of those before.
    """
    t = {k: weighted(graph.tables[k]) for k in ("lineitem", "orders", "customer", "part")}
    delta = {k: changes.tables.get(k, graph.tables[k].limit(0)) for k in t}
    delta = {k: consolidated(weighted(d).select(*t[k].columns)) for k, d in delta.items()}
    money = F.col("l_extendedprice").cast("decimal(38,6)")

    def sums(df: DataFrame, *keys: str) -> DataFrame:
        return df.groupBy(*keys).agg(F.sum("n").alias("n"), F.sum("total").cast("decimal(38,6)").alias("total"))

    def times(df: DataFrame) -> DataFrame:
        return df.withColumns({"n": F.col("n") * F.col(WEIGHT), "total": (F.col("total") * F.col(WEIGHT)).cast("decimal(38,6)")}).drop(WEIGHT)

    def lines(df: DataFrame) -> DataFrame:
        return df.select("l_orderkey", "l_partkey", F.col(WEIGHT).alias("n"), (money * F.col(WEIGHT)).cast("decimal(38,6)").alias("total"))

    customers = lambda df: df.select(F.col("c_custkey").alias("o_custkey"), "c_mktsegment", WEIGHT)
    parts = lambda df: df.select(F.col("p_partkey").alias("l_partkey"), "p_brand", WEIGHT)
    orders = lambda df: df.select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey", WEIGHT)
    by = ("c_mktsegment", "p_brand")

    # kept from the old tables
    segment_of = stored(weighted_join(orders(t["orders"]), customers(t["customer"]), ["o_custkey"]).select("l_orderkey", "c_mktsegment", WEIGHT), "segment_of")
    by_order = stored(sums(lines(t["lineitem"]), "l_orderkey", "l_partkey"), "by_order")
    by_customer = stored(sums(times(by_order.join(orders(t["orders"]), "l_orderkey")), "o_custkey", "l_partkey"), "by_customer")
    by_part = stored(sums(times(by_order.join(segment_of, "l_orderkey")), "l_partkey", "c_mktsegment"), "by_part")
    view = stored(sums(times(by_part.join(parts(t["part"]), "l_partkey")), *by), "revenue")

    new_brand = consolidated(added([parts(t["part"]), parts(delta["part"])]))
    new_customers = consolidated(added([customers(t["customer"]), customers(delta["customer"])]))
    orders_in = weighted_join(orders(delta["orders"]), new_customers, ["o_custkey"]).select("l_orderkey", "c_mktsegment", WEIGHT)
    segments_in = weighted_join(orders(t["orders"]), customers(delta["customer"]), ["o_custkey"]).select("l_orderkey", "c_mktsegment", WEIGHT)
    new_segment = consolidated(added([segment_of, orders_in, segments_in]))
    branded = lambda df: times(df.join(new_brand, "l_partkey"))
    parts_ = [
        view,
        sums(times(by_part.join(parts(delta["part"]), "l_partkey")), *by),
        sums(branded(times(by_customer.join(customers(delta["customer"]), "o_custkey"))), *by),
        sums(branded(times(by_order.join(orders_in, "l_orderkey"))), *by),
        sums(branded(times(lines(delta["lineitem"]).join(new_segment, "l_orderkey"))), *by),
    ]
    return sums(reduce(DataFrame.unionByName, parts_), *by).where("n > 0")


def nested(graph: PropertyGraph, changes: ChangeSet) -> DataFrame:
    """Orders with their lines as an array: a change is merged into the arrays of the orders it touches."""
    def nest(lines: DataFrame) -> DataFrame:
        return lines.groupBy("l_orderkey").agg(F.array_sort(F.collect_list(F.struct("l_partkey", "l_quantity"))).alias("lines"))

    old = stored(nest(graph.tables["lineitem"]), "nested")
    delta = changes.tables["lineitem"]
    touched = delta.select("l_orderkey").distinct()
    flat = old.join(touched, "l_orderkey", "left_semi").select("l_orderkey", F.explode("lines").alias("x")).select("l_orderkey", "x.*")
    bag = added([weighted(flat), delta.select("l_orderkey", "l_partkey", "l_quantity", WEIGHT)])
    return old.join(touched, "l_orderkey", "left_anti").unionByName(nest(rows_of(bag)))


def triples(graph: PropertyGraph) -> DataFrame:
    """Every label, property and edge as (subject, predicate, object)."""
    vertices, edges = graph.nested_vertices(), graph.nested_edges()
    labels = vertices.select(F.col("vertex.id").alias("s"), F.lit("label").alias("p"), F.explode("vertex.labels").alias("o"))
    props = vertices.select(F.col("vertex.id").alias("s"), F.explode("vertex.properties").alias("p", "o"))
    kinds = edges.select(F.col("edge.src").alias("s"), F.col("edge.type").alias("p"), F.col("edge.trg").cast("string").alias("o"))
    more = edges.select(F.col("edge.id").alias("s"), F.explode("edge.properties").alias("p", "o"))
    return labels.unionByName(props).unionByName(kinds).unionByName(more)
