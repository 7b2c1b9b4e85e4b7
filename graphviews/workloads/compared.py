"""The compared techniques on the same views and changes."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import functions as F

from graphviews.baselines import techniques as B
from graphviews.operators.ordering import numbered
from graphviews.sources.commerce import EDGES, VERTICES, commerce, read_tables
from graphviews.sources.graph import PropertyGraph
from graphviews.workloads import maintained as M

QUERIES: dict[str, Callable] = {}
ORACLE_SQL: dict[str, str] = {}


def _mixed(spark, sf_dir):
    graph, batches = M.load_and_changes(spark, sf_dir)
    return graph, batches[0] + batches[1]


def compared(name: str, of: str, technique, **options) -> None:
    """A technique on the text of a maintained view; same result, same SQL."""
    text = M.QUERIES[of].text

    def run(spark, sf_dir):
        graph, changes = _mixed(spark, sf_dir)
        out = technique(graph.plans(text).flat, graph, changes, **options)
        return out[0] if isinstance(out, tuple) else out

    QUERIES[name], ORACLE_SQL[name] = run, M.ORACLE_SQL[of]


compared("b_recompute", "m_join", B.recompute)
compared("b_trigger", "m_join", B.trigger)
compared("b_algebraic_set", "m_distinct", B.algebraic, semantics="set")
compared("b_algebraic_bag", "m_join", B.algebraic)
compared("b_counting", "m_distinct", B.counting)
compared("b_spj", "m_label_change", B.spj)
compared("b_outer_delta", "m_outer_theta", B.outer_delta)
compared("b_semi_delta", "m_semi", B.outer_delta)
compared("b_anti_delta", "m_anti", B.outer_delta)
compared("b_value_counts", "m_minmax", B.value_counts)
compared("b_topk", "m_topk", B.topk)


def register(name: str, sql: str | None):
    def keep(run):
        QUERIES[name] = run
        if sql:
            ORACLE_SQL[name] = sql
        return run

    return keep


@register("b_summary_delta", f"WITH {M.FINAL} SELECT c_mktsegment AS s, count(*)::BIGINT AS n, round(sum(o_totalprice), 1) AS total FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY 1")
def _summary(spark, sf_dir):
    graph, changes = _mixed(spark, sf_dir)
    plan = graph.plans("MATCH (c:Customer)-[:PLACED]->(o:Order) RETURN c.segment AS s, count(*) AS n, sum(o.totalprice) AS total").flat
    return B.summary_delta(plan, graph, changes).withColumn("total", F.round("total", 1))


OUTER_AGG_SQL = f"WITH {M.FINAL} SELECT c_custkey AS c, count(o_orderkey)::BIGINT AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey AND {M.URGENT} GROUP BY 1"


@register("b_outer_agg", OUTER_AGG_SQL)
def _outer_agg(spark, sf_dir):
    graph, changes = _mixed(spark, sf_dir)
    plan = graph.plans("MATCH (c:Customer) OPTIONAL MATCH (c)-[:PLACED]->(o:Order:Urgent) WHERE o.status = 'F' RETURN c.key AS c, count(o) AS n").flat
    return B.outer_agg(plan, graph, changes)


@register("b_summary_outer", f"WITH {M.FINAL} SELECT c_mktsegment AS s, count(*)::BIGINT AS rows, count(o_orderkey)::BIGINT AS n, round(sum(o_totalprice), 1) AS total FROM customer LEFT JOIN orders ON o_custkey = c_custkey AND {M.URGENT} GROUP BY 1")
def _summary_outer(spark, sf_dir):
    """Summary deltas over an outer join: rows, matches and sums by segment."""
    graph, changes = _mixed(spark, sf_dir)
    plan = graph.plans("MATCH (c:Customer) OPTIONAL MATCH (c)-[:PLACED]->(o:Order:Urgent) WHERE o.status = 'F' RETURN c.segment AS s, count(*) AS rows, count(o) AS n, sum(o.totalprice) AS total").flat
    return B.outer_agg(plan, graph, changes).withColumn("total", F.round("total", 1))


@register("b_aggregate_bag", f"WITH {M.FINAL} SELECT count(*)::BIGINT AS n, round(sum(o_totalprice), 1) AS total FROM orders WHERE o_orderpriority = '1-URGENT'")
def _aggregate_bag(spark, sf_dir):
    """A count and a sum of everything, from the old value and the change."""
    graph, changes = _mixed(spark, sf_dir)
    plan = graph.plans("MATCH (o:Order:Urgent) RETURN count(*) AS n, sum(o.totalprice) AS total").flat
    return B.algebraic(plan, graph, changes).withColumn("total", F.round("total", 1))


@register("b_higher_order", f"WITH {M.FINAL} SELECT c_mktsegment AS s, p_brand AS brand, count(*)::BIGINT AS n, CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 6))) AS DOUBLE) AS total FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN part ON p_partkey = l_partkey GROUP BY 1, 2")
def _higher_order(spark, sf_dir):
    """Revenue by segment and brand under changes of all four tables."""
    out = B.higher_order(*_mixed(spark, sf_dir))
    return out.select(F.col("c_mktsegment").alias("s"), F.col("p_brand").alias("brand"), "n", F.col("total").cast("double").alias("total"))


@register("b_nested", f"WITH {M.FINAL} SELECT l_orderkey AS o, count(*)::INT AS n, sum(l_quantity) AS q FROM lineitem GROUP BY 1")
def _nested(spark, sf_dir):
    graph, changes = _mixed(spark, sf_dir)
    out = B.nested(graph, changes)
    return out.select(F.col("l_orderkey").alias("o"), F.size("lines").alias("n"), F.aggregate("lines", F.lit(0.0), lambda s, x: s + x["l_quantity"]).alias("q"))


def _tree(spark, sf_dir):
    """Edges (s, t, e) of the part tree: the old ones, those that come, those that go."""
    part = read_tables(spark, sf_dir)["part"].where("p_partkey > 0").select(F.col("p_partkey").alias("s"), F.expr("(p_partkey - 1) div 4").alias("t"), F.col("p_partkey").alias("e"))
    return part.where("s % 10 <> 3"), part.where("s % 10 = 3"), part.where("s % 50 = 7")


TREE_SQL = "WITH RECURSIVE edge AS (SELECT p_partkey AS c, (p_partkey - 1) // 4 AS p FROM part WHERE p_partkey > 0 AND p_partkey % 50 <> 7), up(c, p) AS (SELECT c, p FROM edge UNION ALL SELECT up.c, edge.p FROM up JOIN edge ON up.p = edge.c) SELECT c AS s, p AS t FROM up"


@register("b_delete_rederive", TREE_SQL)
def _rederive(spark, sf_dir):
    return B.delete_rederive(*_tree(spark, sf_dir))


@register("b_closure_sql", TREE_SQL.replace("SELECT c AS s, p AS t FROM up", "SELECT c AS s, p AS t, count(*)::BIGINT AS n FROM up GROUP BY 1, 2"))
def _closure(spark, sf_dir):
    return B.closure_counts(*_tree(spark, sf_dir))


@register("b_order_keys", f"WITH {M.FINAL} SELECT o_orderkey AS o, row_number() OVER (ORDER BY o_totalprice DESC, o_orderkey) AS place FROM orders")
def _order_keys(spark, sf_dir):
    """Orders by price with order keys; the place is read off the keys alone."""
    orders = read_tables(spark, sf_dir)["orders"].select("o_orderkey", "o_totalprice")
    out = B.order_keys(orders.where("o_orderkey % 10 <> 0"), orders.where("o_orderkey % 10 = 0"), orders.where("o_orderkey % 10 = 1"), [F.col("o_totalprice").desc(), F.col("o_orderkey")])
    return numbered(out, [F.col("_pos")], "place").select(F.col("o_orderkey").alias("o"), F.col("place").cast("long").alias("place"))


@register("b_triples", "SELECT c_mktsegment AS s, count(*)::BIGINT AS n FROM customer JOIN orders ON o_custkey = c_custkey WHERE o_orderstatus = 'F' GROUP BY 1")
def _triples(spark, sf_dir):
    """Orders of status F by segment, from self-joins of one table of triples."""
    graph = commerce(spark, sf_dir)
    small = PropertyGraph(spark, graph.tables, [v for v in VERTICES if v.name in ("customer", "orders")], [e for e in EDGES if e.type == "PLACED"])
    t = B.triples(small)
    placed = t.where("p = 'PLACED'").select(F.col("s").alias("c"), F.col("o").cast("long").alias("order"))
    segment = t.where("p = 'segment'").select(F.col("s").alias("c"), F.col("o").alias("segment"))
    status = t.where("p = 'status' and o = 'F'").select(F.col("s").alias("order"))
    return placed.join(segment, "c").join(status, "order").groupBy(F.col("segment").alias("s")).agg(F.count(F.lit(1)).alias("n"))

