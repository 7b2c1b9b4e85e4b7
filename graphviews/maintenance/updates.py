"""Update statements over generic graph tables, as change sets.

A statement reads first and writes after: what it matches is fixed before any of its
changes counts.  Forms: ``CREATE (:L {k: v})``, ``MATCH ... CREATE (a)-[:T {k: v}]->(b)``,
``MERGE`` in place of CREATE (what is there already, by labels and the given properties or by ends,
type and the given properties, is not made again), ``MATCH ... SET v.k = expr``, ``MATCH ... REMOVE v.k``, ``MATCH ... [DETACH] DELETE v``.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphviews.maintenance.changes import ChangeSet
from graphviews.plans.expr import Lit, PlanError, Prop, Var, to_column
from graphviews.plans.ops import Project, kinds
from graphviews.plans.parser import Parser
from graphviews.sources.graph import PropertyGraph

_HEAD = re.compile(r"\b(create|merge|set|remove|detach\s+delete|delete)\b", re.IGNORECASE)


def apply(graph: PropertyGraph, statement: str) -> ChangeSet:
    """The change set of a statement on a graph of tables vertices and edges (properties a struct)."""
    split = _HEAD.search(statement)
    if not split:
        raise PlanError("an update creates, sets, removes or deletes")
    read, verb, rest = statement[: split.start()].strip(), re.sub(r"\s+", " ", split[1].lower()), statement[split.end():]
    parser = Parser(read or "RETURN 1")
    plan = None
    if read:
        while not parser.peek(""):
            parser.need("match")
            parser.match()
        plan = parser.plan
    writer = Parser(rest)
    writer.plan = plan
    if verb in ("create", "merge"):
        return _create(graph, plan, writer, verb == "merge")
    if plan is None:
        raise PlanError(f"{verb} needs a MATCH")
    if verb in ("set", "remove"):
        return _set(graph, plan, writer, verb == "remove")
    return _delete(graph, plan, writer, verb == "detach delete")


def _rows(graph: PropertyGraph, plan, items) -> DataFrame:
    return graph.query(Project(plan, tuple(items)))


def _next_id(df: DataFrame) -> int:
    return (df.agg(F.max("id")).first()[0] or 0) + 1


def _struct(schema, values: dict):
    """A properties struct with some fields given, the others null."""
    unknown = set(values) - set(schema.names)
    if unknown:
        raise PlanError(f"the table has no property {sorted(unknown)}")
    return F.struct(*[(values.get(f.name, F.lit(None))).cast(f.dataType).alias(f.name) for f in schema.fields])


def _map(writer: Parser) -> dict:
    values = {}
    if writer.take("{"):
        while not writer.take("}"):
            name = writer.name()
            writer.need(":")
            values[name] = writer.expression()
            writer.take(",")
    return values


def _missing(rows: DataFrame, there: DataFrame, tests: dict[str, str], wanted: dict) -> DataFrame:
    """Different rows for which the table has none with equal columns and properties; null equals nothing, so it is always missing."""
    rows = rows.distinct()
    cond = F.lit(True)
    for mine, own in tests.items():
        cond = cond & (F.col(f"_new.{mine}") == F.col(f"_old.{own}"))
    for mine, key in wanted.items():
        cond = cond & (F.col(f"_new.{mine}") == F.col(f"_old.properties.{key}"))
    return rows.alias("_new").join(there.alias("_old"), cond, "left_anti")


def _create(graph, plan, writer: Parser, merge: bool = False) -> ChangeSet:
    vertices, edges = graph.tables["vertices"], graph.tables["edges"]
    writer.need("(")
    var = writer.name() if writer.tokens[writer.at][0] == "name" else None
    labels = []
    while writer.take(":"):
        labels.append(writer.name())
    values = _map(writer)
    writer.need(")")
    if writer.peek(""):
        if plan is not None and var in kinds(plan):
            raise PlanError(f"{var} exists")
        row = graph.spark.range(1).select(*[to_column(e).alias(f"_p_{k}") for k, e in values.items()]) if plan is None else _rows(graph, plan, [("_one", Lit(1)), *((f"_p_{k}", e) for k, e in values.items())])
        if merge:
            there = vertices.where(F.forall(F.array(*map(F.lit, labels)).cast("array<string>"), lambda x: F.array_contains("labels", x)))
            row = _missing(row, there, {}, {f"_p_{k}": k for k in values}) if values else row.distinct().join(there.limit(1).select("id"), F.lit(True), "left_anti")
        made = row.select(
            (F.lit(_next_id(vertices)) + F.monotonically_increasing_id()).cast("long").alias("id"), F.array(*map(F.lit, labels)).cast("array<string>").alias("labels"),
            _struct(vertices.schema["properties"].dataType, {k: F.col(f"_p_{k}") for k in values}).alias("properties"),
        )
        return ChangeSet.inserts(vertices=made)
    if plan is None or var not in kinds(plan):
        raise PlanError("edges are created between matched vertices")
    back = writer.take("<-")
    if not back:
        writer.need("-")
    writer.need("[")
    writer.need(":")
    kind, props = writer.name(), _map(writer)
    writer.need("]")
    writer.need("-" if back else "->")
    writer.need("(")
    other = writer.name()
    writer.need(")")
    if other not in kinds(plan):
        raise PlanError(f"{other} is not bound")
    items = [("_src", Var(other if back else var)), ("_trg", Var(var if back else other)), *((f"_p_{k}", e) for k, e in props.items())]
    rows = _rows(graph, plan, items)
    if merge:
        rows = _missing(rows, edges.where(F.col("type") == kind), {"_src": "src", "_trg": "trg"}, {f"_p_{k}": k for k in props})
    made = rows.select(
        (F.lit(_next_id(edges)) + F.monotonically_increasing_id()).cast("long").alias("id"), F.col("_src").alias("src"), F.col("_trg").alias("trg"), F.lit(kind).alias("type"),
        _struct(edges.schema["properties"].dataType, {k: F.col(f"_p_{k}") for k in props}).alias("properties"),
    )
    return ChangeSet.inserts(edges=made)


def _table_of(plan, var: str) -> str:
    kind = kinds(plan).get(var)
    if kind not in ("vertex", "edge"):
        raise PlanError(f"{var} is no vertex or edge")
    return "vertices" if kind == "vertex" else "edges"


def _set(graph, plan, writer: Parser, remove: bool) -> ChangeSet:
    target = writer.expression() if remove else writer._postfix()
    if not isinstance(target, Prop):
        raise PlanError("SET and REMOVE name a property")
    value = Lit(None)
    if not remove:
        writer.need("=")
        value = writer.expression()
    table = _table_of(plan, target.var)
    df = graph.tables[table]
    new = _rows(graph, plan, [("_id", Var(target.var)), ("_value", value)]).groupBy("_id").agg(F.min("_value").alias("_value"))  # conflicting values: the smallest
    hit = df.join(new, F.col("id") == F.col("_id"))
    kind = {f.name: f.dataType for f in df.schema["properties"].dataType.fields}
    if target.key not in kind:
        raise PlanError(f"the table has no property {target.key}")
    changed = hit.withColumn("properties", F.col("properties").withField(target.key, F.col("_value").cast(kind[target.key])))
    return ChangeSet.updates(table, hit.select(*df.columns), changed.select(*df.columns))


def _delete(graph, plan, writer: Parser, detach: bool) -> ChangeSet:
    var = writer.name()
    table = _table_of(plan, var)
    ids = _rows(graph, plan, [("_id", Var(var))]).distinct()
    gone = graph.tables[table].join(ids, F.col("id") == F.col("_id"), "left_semi")
    if table == "edges":
        return ChangeSet.deletes(edges=gone)
    edges = graph.tables["edges"]
    hanging = edges.join(ids, F.col("src") == F.col("_id"), "left_semi").unionByName(edges.join(ids, F.col("trg") == F.col("_id"), "left_semi")).distinct()
    if not detach:
        if hanging.limit(1).count():
            raise PlanError(f"{var} still has edges: DETACH DELETE removes them too")
        return ChangeSet.deletes(vertices=gone)
    return ChangeSet.deletes(vertices=gone, edges=hanging)
