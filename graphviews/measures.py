"""Measures of views and plans: times, state, traffic, widths, joins, exactness, crossover, coverage, lookups."""

from __future__ import annotations

import time
from dataclasses import asdict, dataclass, field

from pyspark.sql import DataFrame

from graphviews.maintenance.changes import ChangeSet
from graphviews.maintenance.network import Network
from graphviews.operators.lowering import Lowering
from graphviews.plans.ops import ScanEdges, ScanVertices
from graphviews.plans.rewrite import Options, flat_columns, join_count
from graphviews.sources.graph import WEIGHT, PropertyGraph, consolidated


def timed(df: DataFrame) -> float:
    """Seconds to compute all rows and columns."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


@dataclass
class Measured:
    """One view under one change set."""

    load_s: float = 0.0
    refresh_s: list[float] = field(default_factory=list)
    recompute_s: float = 0.0
    state_rows: int = 0
    state_bytes: int = 0
    leaf_rows: int = 0
    node_rows: dict[str, int] = field(default_factory=dict)
    flat_width: int = 0
    nested_width: int = 0
    joins: int = 0
    joins_unfused: int = 0
    exact: bool = True
    delta_exact: bool = True

    def row(self) -> dict:
        return asdict(self)


def same_bag(a: DataFrame, b: DataFrame) -> bool:
    """Whether two bags have the same rows as often."""
    a = a.select(*b.columns)
    return a.exceptAll(b).limit(1).count() == 0 and b.exceptAll(a).limit(1).count() == 0


def nested_columns(graph: PropertyGraph, leaf) -> int:
    """Values of a leaf's tuple if vertices and edges came whole: ids, labels, type and all properties."""
    vertex = lambda labels: max((len(s.props) + 2 for s in graph.vertices.values() if graph.may_have(s, labels)), default=0)
    if isinstance(leaf, ScanVertices):
        return vertex(leaf.labels)
    return vertex(leaf.v_labels) + vertex(leaf.w_labels) + max((len(s.props) + 4 for s in graph.edge_sources(leaf.types)), default=0)


def state_bytes(network: Network) -> int:
    """Bytes of all runs in the shared folder."""
    spark = network.graph.spark
    conf, jvm = spark.sparkContext._jsc.hadoopConfiguration(), spark.sparkContext._jvm
    total = 0
    for node in network.root.walk():
        for run in node.runs:
            for name in run.inputFiles():
                path = jvm.org.apache.hadoop.fs.Path(name)
                total += path.getFileSystem(conf).getFileStatus(path).getLen()
    return total


def measure(graph: PropertyGraph, text: str, changes: list[ChangeSet], mode: str = "trail", check: bool = True) -> Measured:
    """Load a view, refresh it by the change sets, and compare with recomputation."""
    plans, out = graph.plans(text, mode), Measured()
    began = time.perf_counter()
    network = Network(graph, plans.flat, label="measured").load()
    out.load_s = time.perf_counter() - began
    out.leaf_rows = sum(Lowering(network.graph).df(n).count() for n in network.plan.walk() if isinstance(n, (ScanVertices, ScanEdges)))
    before = network.read()
    for c in changes:
        report = network.refresh(c)
        out.refresh_s.append(report.seconds)
        for name, n in report.rows.items():
            out.node_rows[name] = out.node_rows.get(name, 0) + n
    final = network.graph.with_tables({t: _rows(df) for t, df in network.graph.tables.items()})
    again = final.query(text, mode)
    out.recompute_s = timed(again)
    out.state_rows, out.state_bytes = network.state_rows(), state_bytes(network)
    leaves = [n for n in plans.flat.walk() if isinstance(n, (ScanVertices, ScanEdges))]
    out.flat_width = sum(len(flat_columns(n)) for n in leaves)
    out.nested_width = sum(nested_columns(graph, n) for n in leaves)
    out.joins, out.joins_unfused = join_count(plans.flat), join_count(graph.plans(text, mode, Options(fuse=False, drop_endpoint=False)).flat)
    if check:
        now = network.read()
        out.exact = same_bag(now, again)
        deltas = [d for g, d in network.history.items() if g and d is not None]
        total = consolidated(deltas[0] if len(deltas) == 1 else _union(deltas)) if deltas else None
        if total is not None:
            plus, minus = _rows(total.where(f"{WEIGHT} > 0")), _rows(total.where(f"{WEIGHT} < 0").withColumn(WEIGHT, -total[WEIGHT]))
            out.delta_exact = same_bag(now.exceptAll(before.select(*now.columns)), plus.select(*now.columns)) and same_bag(before.exceptAll(now.select(*before.columns)), minus.select(*before.columns))
    return out


def _union(parts: list[DataFrame]) -> DataFrame:
    from functools import reduce

    return reduce(DataFrame.unionByName, parts)


def _rows(df: DataFrame) -> DataFrame:
    from graphviews.sources.graph import _plain_rows

    return _plain_rows(df)


def crossover(graph: PropertyGraph, text: str, table: str, key: str, shares: list[float]) -> list[tuple[float, float, float]]:
    """(share of a table that changes, refresh seconds, recompute seconds) for each share, by deletes of hashed keys."""
    from pyspark.sql import functions as F

    out = []
    for share in shares:
        network = Network(graph, graph.plans(text).flat, label="crossover").load()
        gone = graph.tables[table].where(F.pmod(F.xxhash64(key), F.lit(1_000_000)) < int(share * 1_000_000))
        report = network.refresh(ChangeSet.deletes(**{table: gone}))
        left = graph.tables[table].join(gone.select(key).distinct(), key, "left_anti").select(*graph.tables[table].columns)
        out.append((share, report.seconds, timed(graph.with_tables({table: left}).query(text))))
    return out


def ablations(graph: PropertyGraph, text: str, mode: str = "trail") -> dict[str, tuple[int, float]]:
    """(joins, seconds) of a query with each rewrite switched off."""
    cases = {"all": Options(), "no fusion": Options(fuse=False), "endpoint joins kept": Options(drop_endpoint=False), "no left-deep order": Options(left_deep=False)}
    return {name: (join_count(graph.plans(text, mode, o).flat), timed(graph.query(text, mode, o))) for name, o in cases.items()}


def traffic(spark) -> dict[str, int]:
    """Jobs and stages run so far, bytes shuffled and read; two of them differ by what lies between."""
    store = spark.sparkContext._jsc.sc().statusStore()
    jobs = store.jobsList(None)
    none = spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0)
    stages = store.stageList(None, False, False, none, None)
    out = {"jobs": jobs.size(), "stages": 0, "shuffle_bytes": 0, "input_bytes": 0}
    for k in range(stages.size()):
        stage = stages.apply(k)
        out["stages"] += 1
        out["shuffle_bytes"] += stage.shuffleWriteBytes()
        out["input_bytes"] += stage.inputBytes()
    return out


#: One statement for each feature of the language.
COVERAGE = {
    "vertex scan": "MATCH (a:A) RETURN a", "property": "MATCH (a) RETURN a.name AS n", "out": "MATCH (a)-[:T]->(b) RETURN a, b", "in": "MATCH (a)<-[:T]-(b) RETURN a, b", "both": "MATCH (a)-[:T]-(b) RETURN a, b",
    "variable length": "MATCH (a)-[e:T*1..2]->(b) RETURN a, length(e) AS n", "unbounded": "MATCH (a)-[e:T*]->(b) RETURN a, b", "zero hops": "MATCH (a)-[e:T*0..]->(b) RETURN a, b",
    "several patterns": "MATCH (a)-[:T]->(b), (b)-[:T]->(c) RETURN a, c", "optional": "MATCH (a) OPTIONAL MATCH (a)-[:T]->(b) WHERE a.age < b.age RETURN a, b",
    "pattern": "MATCH (a) WHERE (a)-[:T]->() RETURN a", "negated pattern": "MATCH (a) WHERE NOT (a)-[:T]->() RETURN a", "pattern under or": "MATCH (a) WHERE a.age > 3 OR (a)-[:T]->() RETURN a",
    "label test": "MATCH (a) WHERE a:B RETURN a", "unwind": "MATCH (a) UNWIND a.speaks AS s RETURN s", "unwind with place": "MATCH (a) UNWIND a.speaks AS s AT i RETURN s, i",
    "distinct": "MATCH (a) RETURN DISTINCT a.name AS n", "group": "MATCH (a) RETURN a.name AS n, count(*) AS k", "having": "MATCH (a) WITH a.name AS n, count(*) AS k WHERE k > 1 RETURN n",
    "order": "MATCH (a) RETURN a.name AS n ORDER BY n DESC SKIP 1 LIMIT 2", "collect": "MATCH (a) RETURN collect(a.name) AS all", "distinct aggregate": "MATCH (a) RETURN count(DISTINCT a.name) AS k",
}


def coverage(graph: PropertyGraph, statements: dict[str, str] = COVERAGE) -> dict[str, str]:
    """For each statement ``maintained``, ``read`` where only one-time evaluation works, or the error."""
    out = {}
    for name, text in statements.items():
        try:
            graph.query(text).schema
            out[name] = "read"
            Network(graph, graph.plans(text).flat, label="covered").load()
            out[name] = "maintained"
        except Exception as error:
            if name not in out:
                out[name] = f"{type(error).__name__}: {error}"[:100]
    return out
