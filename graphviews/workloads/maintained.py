"""Maintained views under the update streams; each is checked against the query on the final tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import functions as F

from graphviews.maintenance.catalog import ViewCatalog
from graphviews.maintenance.changes import ChangeSet
from graphviews.maintenance.network import Network
from graphviews.sources.commerce import EDGES, VERTICES, read_tables
from graphviews.sources.graph import PropertyGraph
from graphviews.sources.shared import new_path
from graphviews.workloads.graph import CLOSURE, KNOWS, RUNNING, RUNNING_SQL

QUERIES: dict[str, Callable] = {}
ORACLE_SQL: dict[str, str] = {}

ROTATED = "CASE c_mktsegment WHEN 'AUTOMOBILE' THEN 'BUILDING' WHEN 'BUILDING' THEN 'FURNITURE' WHEN 'FURNITURE' THEN 'HOUSEHOLD' WHEN 'HOUSEHOLD' THEN 'MACHINERY' ELSE 'AUTOMOBILE' END"
FINAL = f"""orders AS (SELECT * FROM main.orders WHERE o_orderkey % 10 <> 1),
lineitem AS (SELECT * FROM main.lineitem WHERE l_orderkey % 10 <> 1),
customer AS (SELECT c_custkey, c_name, c_nationkey, c_acctbal, CASE WHEN c_custkey % 7 = 0 THEN {ROTATED} ELSE c_mktsegment END AS c_mktsegment FROM main.customer),
part AS (SELECT * FROM main.part WHERE p_partkey % 50 <> 7)"""


def load_and_changes(spark, sf_dir: str) -> tuple[PropertyGraph, list[ChangeSet]]:
    """The graph less the rows to come, and the batches: orders in, orders out, segments and parts changed."""
    t = read_tables(spark, sf_dir)
    orders, lines, customers, parts = t["orders"], t["lineitem"], t["customer"], t["part"]
    old = {**t, "orders": orders.where("o_orderkey % 10 <> 0"), "lineitem": lines.where("l_orderkey % 10 <> 0")}
    turned = customers.where("c_custkey % 7 = 0")
    insert = ChangeSet.inserts(orders=orders.where("o_orderkey % 10 = 0"), lineitem=lines.where("l_orderkey % 10 = 0"))
    mixed = (
        ChangeSet.deletes(orders=orders.where("o_orderkey % 10 = 1"), lineitem=lines.where("l_orderkey % 10 = 1"))
        + ChangeSet.updates("customer", turned, turned.withColumn("c_mktsegment", F.expr(ROTATED)))
        + ChangeSet.deletes(part=parts.where("p_partkey % 50 = 7"))
    )
    return PropertyGraph(spark, old, VERTICES, EDGES), [insert, mixed]


def maintained(name: str, text: str, sql: str, mode: str = "trail", finish=None) -> None:
    """Register a view that is loaded, refreshed twice and read."""
    def run(spark, sf_dir):
        graph, batches = load_and_changes(spark, sf_dir)
        network = Network(graph, graph.plans(text, mode).flat, label=name).load()
        for changes in batches:
            network.refresh(changes)
        out = network.read()
        return finish(out) if finish else out

    run.text = text
    QUERIES[name] = run
    sql = sql.strip()
    ORACLE_SQL[name] = sql.replace("WITH RECURSIVE ", f"WITH RECURSIVE {FINAL}, ", 1) if sql.startswith("WITH RECURSIVE") else sql.replace("WITH ", f"WITH {FINAL}, ", 1) if sql.startswith("WITH ") else f"WITH {FINAL} {sql}"


URGENT = "o_orderpriority = '1-URGENT' AND o_orderstatus = 'F'"
maintained("m_select", "MATCH (o:Order) WHERE o.totalprice > 200000 RETURN o.key AS o", "SELECT o_orderkey AS o FROM orders WHERE o_totalprice > 200000")
maintained("m_project", "MATCH (o:Order) RETURN o.status AS s, o.priority AS p", "SELECT o_orderstatus AS s, o_orderpriority AS p FROM orders")
maintained("m_union", "MATCH (a:Customer)-[:KNOWS]-(b:Customer) RETURN a.key AS a, b.segment AS s", f"WITH {KNOWS} SELECT a, c_mktsegment AS s FROM (SELECT a, b FROM knows UNION ALL SELECT b, a FROM knows) JOIN customer ON c_custkey = b")
maintained("m_unwind", "MATCH (p:Part) UNWIND p.words AS w RETURN w, p.size AS size", "SELECT w, size FROM (SELECT unnest(string_split(p_name, ' ')) AS w, p_size AS size FROM part)")
maintained("m_join", "MATCH (c:Customer)-[:PLACED]->(o:Order)-[l:CONTAINS]->(p:Part) RETURN c.segment AS s, p.brand AS brand, l.quantity AS q",
           "SELECT c_mktsegment AS s, p_brand AS brand, l_quantity AS q FROM orders JOIN customer ON c_custkey = o_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN part ON p_partkey = l_partkey")
maintained("m_selfjoin", "MATCH (a:Customer)-[:KNOWS]->(b:Customer)-[:KNOWS]->(c:Customer) WHERE a.segment = c.segment RETURN a.key AS a, c.key AS c",
           f"WITH {KNOWS} SELECT x.a AS a, y.b AS c FROM knows x JOIN knows y ON x.b = y.a JOIN customer p ON p.c_custkey = x.a JOIN customer q ON q.c_custkey = y.b WHERE p.c_mktsegment = q.c_mktsegment")
maintained("m_distinct", "MATCH (o:Order)-[:SHIPPED_BY]->(s:Supplier) RETURN DISTINCT s.key AS s, o.priority AS p", "SELECT DISTINCT l_suppkey AS s, o_orderpriority AS p FROM lineitem JOIN orders ON o_orderkey = l_orderkey")
maintained("m_semi", "MATCH (c:Customer) WHERE (c)-[:PLACED]->(:Order:Urgent {status: 'F'}) RETURN c.key AS c, c.segment AS s", f"SELECT c_custkey AS c, c_mktsegment AS s FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND {URGENT})")
maintained("m_anti", "MATCH (c:Customer) WHERE NOT (c)-[:PLACED]->(:Order:Urgent {status: 'F'}) RETURN c.key AS c, c.segment AS s", f"SELECT c_custkey AS c, c_mktsegment AS s FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND {URGENT})")
maintained("m_outer", "MATCH (c:Customer) OPTIONAL MATCH (c)-[:PLACED]->(o:Order:Urgent) WHERE o.status = 'F' RETURN c.key AS c, o.key AS o", f"SELECT c_custkey AS c, o_orderkey AS o FROM customer LEFT JOIN orders ON o_custkey = c_custkey AND {URGENT}")
maintained("m_outer_theta", "MATCH (c:Customer) OPTIONAL MATCH (c)-[:PLACED]->(o:Order) WHERE o.totalprice > c.acctbal * 20 RETURN c.segment AS s, o.key AS o", "SELECT c_mktsegment AS s, o_orderkey AS o FROM customer LEFT JOIN orders ON o_custkey = c_custkey AND o_totalprice > c_acctbal * 20")
maintained("m_group_sum", "MATCH (c:Customer)-[:PLACED]->(o:Order) RETURN c.segment AS s, count(*) AS n, round(sum(o.totalprice), 1) AS total", "SELECT c_mktsegment AS s, count(*)::BIGINT AS n, round(sum(o_totalprice), 1) AS total FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY 1")
maintained("m_group_distinct", "MATCH (o:Order)-[:CONTAINS]->(p:Part) RETURN p.key AS p, count(DISTINCT o) AS n", "SELECT l_partkey AS p, count(DISTINCT l_orderkey)::BIGINT AS n FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY 1")
maintained("m_minmax", "MATCH (c:Customer)-[:PLACED]->(o:Order) RETURN c.key AS c, min(o.totalprice) AS low, max(o.totalprice) AS high", "SELECT o_custkey AS c, min(o_totalprice) AS low, max(o_totalprice) AS high FROM orders GROUP BY 1")
maintained("m_stdev", "MATCH (o:Order)-[l:CONTAINS]->(p:Part) RETURN p.key AS p, round(stdev(l.quantity), 4) AS spread", "SELECT l_partkey AS p, round(stddev_samp(l_quantity), 4) AS spread FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY 1")
maintained("m_agg_on_agg", "MATCH (c:Customer)-[:PLACED]->(:Order) WITH c, count(*) AS k RETURN k, count(*) AS n", "SELECT k, count(*)::BIGINT AS n FROM (SELECT o_custkey, count(*) AS k FROM orders GROUP BY 1) GROUP BY 1")
maintained("m_trans_delete", "MATCH (a:Part)-[e:SUBCLASS_OF*1..]->(b:Part) RETURN a.key AS a, b.key AS b, length(e) AS n",
           "WITH RECURSIVE edge AS (SELECT p_partkey AS c, (p_partkey - 1) // 4 AS p FROM part WHERE p_partkey > 0), up(c, p, n) AS (SELECT c, p, 1 FROM edge UNION ALL SELECT up.c, edge.p, n + 1 FROM up JOIN edge ON up.p = edge.c) SELECT up.c AS a, up.p AS b, n::INT AS n FROM up JOIN part ON p_partkey = up.p")
maintained("m_topk", "MATCH (o:Order) RETURN o.key AS o, o.totalprice AS price ORDER BY price DESC, o LIMIT 15", "SELECT o_orderkey AS o, o_totalprice AS price FROM orders ORDER BY price DESC, o LIMIT 15")
maintained("m_vertex_change", "MATCH (a:Customer)-[:KNOWS]-(b:Customer) WHERE a.segment = b.segment RETURN a.key AS a, count(b) AS n", f"WITH {KNOWS}, k AS (SELECT a, b FROM knows UNION ALL SELECT b, a FROM knows) SELECT k.a AS a, count(*)::BIGINT AS n FROM k JOIN customer x ON x.c_custkey = k.a JOIN customer y ON y.c_custkey = k.b WHERE x.c_mktsegment = y.c_mktsegment GROUP BY 1")
maintained("m_label_change", "MATCH (c:BUILDING)-[:PLACED]->(o:Order) RETURN c.key AS c, o.key AS o", "SELECT o_custkey AS c, o_orderkey AS o FROM orders JOIN customer ON c_custkey = o_custkey WHERE c_mktsegment = 'BUILDING'")
maintained("m_global", "MATCH (o:Order:Urgent) RETURN count(*) AS n, max(o.totalprice) AS top", "SELECT count(*)::BIGINT AS n, max(o_totalprice) AS top FROM orders WHERE o_orderpriority = '1-URGENT'")
maintained("m_multiway", "MATCH (a:Customer)-[:KNOWS]->(b:Customer)-[:KNOWS]->(c:Customer)<-[:KNOWS]-(a) RETURN a.key AS a, b.key AS b, c.segment AS s", f"WITH {KNOWS} SELECT x.a AS a, x.b AS b, c_mktsegment AS s FROM knows x JOIN knows y ON x.b = y.a JOIN knows z ON z.a = x.a AND z.b = y.b JOIN customer ON c_custkey = y.b")
maintained("m_pattern_or", "MATCH (c:Customer) WHERE c.acctbal > 9000 OR (c)-[:PLACED]->(:Order:Urgent {status: 'F'}) RETURN c.key AS c, c.segment AS s", f"SELECT c_custkey AS c, c_mktsegment AS s FROM customer WHERE c_acctbal > 9000 OR EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND {URGENT})")
maintained("w_running_maint", RUNNING, RUNNING_SQL, mode="reach")


def _two_tables(name: str, text: str, sql: str) -> None:
    """A view over documents and their labels, where both come and go."""
    def run(spark, sf_dir):
        t = read_tables(spark, sf_dir)
        docs, labels = t["documents"], t["labels"]
        graph = PropertyGraph(spark, {**t, "documents": docs.where("doc_id % 10 <> 0"), "labels": labels.where("doc_id % 3 <> 0")}, VERTICES, EDGES)
        network = Network(graph, graph.plans(text).flat, label=name).load()
        network.refresh(ChangeSet.inserts(documents=docs.where("doc_id % 10 = 0"), labels=labels.where("doc_id % 3 = 0")))
        network.refresh(ChangeSet.deletes(documents=docs.where("doc_id % 10 = 1"), labels=labels.where("doc_id % 5 = 1")))
        return network.read()

    QUERIES[name] = run
    ORACLE_SQL[name] = f"WITH documents AS (SELECT * FROM main.documents WHERE doc_id % 10 <> 1), labels AS (SELECT * FROM main.labels WHERE doc_id % 5 <> 1) {sql}"


_two_tables("m_doc_opt", "MATCH (d:Document) OPTIONAL MATCH (d)-[:SAME_TEXT]->(f:Document) WHERE f.toxic = 1 RETURN d.key AS d, d.quality AS quality, f.key AS f",
            "SELECT d.doc_id AS d, l.quality AS quality, x.f AS f FROM documents d LEFT JOIN labels l USING (doc_id) LEFT JOIN (SELECT c.doc_id, g.f FROM documents c JOIN (SELECT md5(trim(lower(text))) AS m, min(doc_id) AS f FROM documents GROUP BY 1) g ON md5(trim(lower(c.text))) = g.m AND c.doc_id > g.f JOIN labels k ON k.doc_id = g.f AND k.toxic = 1) x ON x.doc_id = d.doc_id")
_two_tables("m_any_vertex", "MATCH (x) WHERE x.toxic = 1 OR x.lang = 'de' RETURN x.lang AS lang, count(*) AS n, count(x.toxic) AS known",
            "SELECT lang, count(*)::BIGINT AS n, count(toxic)::BIGINT AS known FROM documents LEFT JOIN labels USING (doc_id) WHERE toxic = 1 OR lang = 'de' GROUP BY 1")


MANY = 21


def _many_batches(spark, sf_dir):
    """Sums by segment after a batch for every remainder of the order key; runs and plans stay bounded."""
    t = read_tables(spark, sf_dir)
    graph = PropertyGraph(spark, {**t, "orders": t["orders"].limit(0)}, VERTICES, EDGES)
    network = Network(graph, graph.plans("MATCH (c:Customer)-[:PLACED]->(o:Order) RETURN c.segment AS s, count(*) AS n, round(sum(o.totalprice), 1) AS total, max(o.totalprice) AS top").flat, label="m_many_batches").load()
    for i in range(MANY):
        network.refresh(ChangeSet.inserts(orders=t["orders"].where(f"o_orderkey % {MANY} = {i}")), f"batch {i}")
    return network.read()


QUERIES["m_many_batches"] = _many_batches
ORACLE_SQL["m_many_batches"] = "SELECT c_mktsegment AS s, count(*)::BIGINT AS n, round(sum(o_totalprice), 1) AS total, max(o_totalprice) AS top FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY 1"


def _catalogued(policy: str, restart: bool):
    """A view of a catalogue in a folder, under both batches, with a restart between them."""
    def run(spark, sf_dir):
        graph, batches = load_and_changes(spark, sf_dir)
        folder = new_path(spark, "catalogue")
        catalog = ViewCatalog(graph, folder if restart else None)
        catalog.create("spread", "MATCH (c:Customer)-[:PLACED]->(o:Order) RETURN c.segment AS s, o.status AS status, count(*) AS n, min(o.totalprice) AS low", policy=policy)
        for k, changes in enumerate(batches):
            catalog.refresh(changes, f"batch {k}")
            if restart:
                catalog = ViewCatalog.open(graph, folder)
                catalog.refresh(changes, f"batch {k}")
        return catalog.views["spread"].read()

    return run


for _name, _policy, _restart in (("m_restart", "immediate", True), ("m_deferred", "deferred", False), ("m_recomputed", "recomputed", False)):
    QUERIES[_name] = _catalogued(_policy, _restart)
    ORACLE_SQL[_name] = f"WITH {FINAL} SELECT c_mktsegment AS s, o_orderstatus AS status, count(*)::BIGINT AS n, min(o_totalprice) AS low FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY 1, 2"


def _insert_into_tree(spark, sf_dir):
    """Closure of the part tree, where a tenth of the parts comes later."""
    t = read_tables(spark, sf_dir)
    graph = PropertyGraph(spark, {**t, "part": t["part"].where("p_partkey % 10 <> 3")}, VERTICES, EDGES)
    network = Network(graph, graph.plans("MATCH (a:Part)-[e:SUBCLASS_OF*1..]->(b:Part) RETURN a.key AS a, b.key AS b, length(e) AS n").flat, label="m_trans_insert").load()
    network.refresh(ChangeSet.inserts(part=t["part"].where("p_partkey % 10 = 3")))
    return network.read()


QUERIES["m_trans_insert"] = _insert_into_tree
ORACLE_SQL["m_trans_insert"] = f"WITH RECURSIVE {CLOSURE} SELECT c AS a, p AS b, n::INT AS n FROM up"


def _delta_only(spark, sf_dir):
    """The signed change of a grouped view under one batch of inserts."""
    graph, batches = load_and_changes(spark, sf_dir)
    network = Network(graph, graph.plans("MATCH (o:Order) RETURN o.status AS s, count(*) AS n").flat, label="m_delta_only").load()
    return network.refresh(batches[0]).delta.withColumnRenamed("__w", "w")


QUERIES["m_delta_only"] = _delta_only
ORACLE_SQL["m_delta_only"] = """SELECT s, n, w::BIGINT AS w FROM (
SELECT o_orderstatus AS s, count(*)::BIGINT AS n, 1 AS w FROM orders GROUP BY 1
UNION ALL SELECT o_orderstatus, count(*), -1 FROM orders WHERE o_orderkey % 10 <> 0 GROUP BY 1)"""


def _running_delta(spark, sf_dir):
    """The running example's change when one line of a new buyer comes in, and when it goes again."""
    t = read_tables(spark, sf_dir)
    graph = PropertyGraph(spark, t, VERTICES, EDGES)
    network = Network(graph, graph.plans(RUNNING, "reach").flat, label="w_running_delta").load()
    buyers = network.read().select(F.col("name").alias("c_name"))
    lonely = t["customer"].join(buyers, "c_name", "left_anti").join(t["orders"].select(F.col("o_custkey").alias("c_custkey"), "o_orderkey"), "c_custkey")
    order = lonely.orderBy("c_custkey", "o_orderkey").select("o_orderkey").limit(1)
    line = t["lineitem"].orderBy(*t["lineitem"].columns).limit(1).drop("l_orderkey", "l_partkey", "l_quantity").crossJoin(order.withColumnRenamed("o_orderkey", "l_orderkey"))
    line = line.withColumns({"l_partkey": F.lit(20).cast("long"), "l_quantity": F.lit(50.0)}).select(*t["lineitem"].columns)
    come = network.refresh(ChangeSet.inserts(lineitem=line)).delta
    go = network.refresh(ChangeSet.deletes(lineitem=line)).delta
    rows = [d.select("name", F.col("__w").alias("w"), F.lit(i).alias("step")) for i, d in ((1, come), (2, go)) if d is not None]
    return rows[0].unionByName(rows[1]) if len(rows) == 2 else spark.createDataFrame([], "name string, w long, step int")


QUERIES["w_running_delta"] = _running_delta
ORACLE_SQL["w_running_delta"] = RUNNING_SQL.rstrip().removesuffix("SELECT name FROM nf WHERE n < 1").rstrip() + """, res AS (SELECT name FROM nf WHERE n < 1),
cand AS (SELECT c_custkey, c_name, c_mktsegment FROM customer JOIN orders ON o_custkey = c_custkey WHERE c_name NOT IN (SELECT name FROM res) ORDER BY c_custkey, o_orderkey LIMIT 1),
near AS (SELECT c_name AS name, (SELECT count(DISTINCT y.c_custkey) FROM k JOIN customer y ON y.c_custkey = k.b WHERE k.a = cand.c_custkey AND y.c_mktsegment = cand.c_mktsegment) AS n FROM cand)
SELECT name, w, step FROM near, (VALUES (1::BIGINT, 1), (-1, 2)) t(w, step) WHERE n < 1"""
