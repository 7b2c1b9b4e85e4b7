"""Vertices and edges laid out for lookups by id, label and type.

Ids are written once as tables partitioned by what a lookup gives: the kind of vertex
or the type of edge, then a bucket of the id (of either end, for edges).  Each further
constraint prunes folders before a file is opened; inside a file rows are sorted by id,
so the statistics of its row groups prune the rest.  Labels that hold for a whole kind
are resolved without reading anything.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphviews.sources.graph import PropertyGraph
from graphviews.sources.shared import new_path

BUCKETS = 16


def bucket_of(column) -> F.Column:
    return F.pmod(F.xxhash64(column), F.lit(BUCKETS)).cast("int")


class LeafIndex:
    """Lookups of vertices and edges of a graph; build() writes it."""

    def __init__(self, graph: PropertyGraph, vertices: str, edges: str):
        self.graph, self.paths = graph, (vertices, edges)

    @classmethod
    def build(cls, graph: PropertyGraph) -> LeafIndex:
        spark = graph.spark
        where = new_path(spark, "index-vertices"), new_path(spark, "index-edges")
        kinds = [graph.scan_vertices("id", (), ("@labels",), only=s.name).select("id", F.col("id__@labels").alias("labels"), F.lit(s.name).alias("kind")) for s in graph.vertices.values()]
        types: dict[str, list] = {}
        for s in graph.edges:
            types.setdefault(s.type, []).append(s)
        walks = [
            graph.of_sources(list(graph.vertices.values()), sources).scan_edges("src", (), "id", (t,), "trg", (), ends=False).select("id", "src", "trg", F.lit(t).alias("type"))
            for t, sources in types.items()
        ]
        for parts, path, key, folder in ((kinds, where[0], "id", "kind"), (walks, where[1], "src", "type")):
            rows = reduce(DataFrame.unionByName, parts).withColumn("bucket", bucket_of(key))
            rows.repartition(folder, "bucket").sortWithinPartitions(folder, "bucket", key).write.partitionBy(folder, "bucket").parquet(path)
        return cls(graph, *where)

    def _pruned(self, path: str, folder: str, names: list[str] | None, key: str, ids: list[int] | None) -> DataFrame:
        df = self.graph.spark.read.parquet(path)
        if names is not None:
            df = df.where(F.col(folder).isin(names))
        if ids is not None:
            buckets = self.graph.spark.createDataFrame([(i,) for i in ids], "id long").select(bucket_of("id").alias("b")).distinct().collect()  # no more than buckets
            df = df.where(F.col("bucket").isin([r["b"] for r in buckets]) & F.col(key).isin(ids))
        return df

    def vertices(self, labels: tuple[str, ...] = (), ids: list[int] | None = None) -> DataFrame:
        """Vertices (id, labels) with all the labels, of the ids if some are given."""
        kinds = [s.name for s in self.graph.vertices.values() if self.graph.may_have(s, labels)]
        df = self._pruned(self.paths[0], "kind", kinds, "id", ids)
        return df.where(F.forall(F.array(*map(F.lit, labels)).cast("array<string>"), lambda x: F.array_contains("labels", x))).select("id", "labels")

    def edges(self, types: tuple[str, ...] = (), labels: tuple[str, ...] = (), ids: list[int] | None = None) -> DataFrame:
        """Edges (id, src, trg) of the types that leave vertices with all the labels, of the ids if some are given."""
        fit = [s for s in self.graph.edge_sources(types) if self.graph.may_have(self.graph.vertices[s.source], labels)]
        df = self._pruned(self.paths[1], "type", sorted({s.type for s in fit}), "src", ids)
        if any(not set(labels) <= set(self.graph.vertices[s.source].labels) for s in self.graph.edge_sources(tuple({s.type for s in fit}))):
            df = df.join(self.vertices(labels, ids).select(F.col("id").alias("src")), "src", "left_semi")
        return df.select("id", "src", "trg")


def lookup_cost(found: DataFrame) -> tuple[int, int, int]:
    """(files opened, rows that the scans gave, rows found) of a lookup, from the metrics of its run."""
    run = found._jdf.queryExecution()
    n = run.toRdd().count()
    files = rows = 0
    todo = [run.executedPlan()]
    while todo:
        plan = todo.pop()
        kind = plan.getClass().getSimpleName()
        if kind == "AdaptiveSparkPlanExec":
            todo.append(plan.executedPlan())
            continue
        leaves = plan.collectLeaves()
        for k in range(leaves.size()):
            leaf = leaves.apply(k)
            if leaf.getClass().getSimpleName().endswith("QueryStageExec"):
                todo.append(leaf.plan())
            elif leaf.metrics().contains("numFiles"):
                files += leaf.metrics().apply("numFiles").value()
                rows += leaf.metrics().apply("numOutputRows").value()
    return files, rows, n
