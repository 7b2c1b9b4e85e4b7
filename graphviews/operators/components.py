"""Connected components of an undirected graph, and what needs no walk once they are known."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphviews.sources.shared import dropped, run_of, stored

BLOCKS = 32


def _stars(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The components of a task's edges as stars, each node with the smallest one; all ends of edges are there."""
    up: dict[int, int] = {}

    def root(x: int) -> int:
        up.setdefault(x, x)
        while up[x] != x:
            up[x] = x = up[up[x]]
        return x

    for batch in batches:
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            ra, rb = root(a), root(b)
            if ra != rb:
                up[max(ra, rb)] = min(ra, rb)
    nodes = pa.array(list(up), pa.int64())
    yield pa.RecordBatch.from_arrays([nodes, pa.array([root(x) for x in list(up)], pa.int64())], ["s", "t"])


def components(edges: DataFrame) -> DataFrame:
    """(node, label) of all ends of edges (s, t): label is the smallest node of the component.

    Tasks first reduce their edges to stars.  Then each node takes the smallest label next to
    it and the label of its label, so labels travel at doubling speed, until none changes.
    """
    stars = edges.select(F.col("s").cast("long"), F.col("t").cast("long")).where("s is not null and t is not null").mapInArrow(_stars, "s long, t long")
    turned = F.explode(F.array(F.struct(F.col("s").alias("u"), F.col("t").alias("v")), F.struct(F.col("t").alias("u"), F.col("s").alias("v"))))
    both = stored(stars.select(turned.alias("x")).select("x.*").distinct(), "stars")
    labels = stored(both.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("v")).select("node", F.least("node", "v").alias("label")), "labels")
    while True:
        near = both.join(labels.select(F.col("node").alias("v"), "label"), "v").groupBy(F.col("u").alias("node")).agg(F.min("label").alias("near"))
        hooked = stored(labels.join(near, "node").select("node", F.col("label").alias("old"), F.least("label", "near").alias("label")), "hooked")
        jump = hooked.select(F.col("node").alias("label"), F.col("label").alias("next"))
        following = run_of(hooked.join(jump, "label").select("node", "old", F.least("label", "next").alias("label")), "labels", mark=F.col("old") > F.col("label"))
        dropped(labels)
        dropped(hooked)
        labels = following.df
        if not following.marked:
            dropped(both)
            return labels.select("node", "label")


def reached(seeds: DataFrame, edges: DataFrame, low: int) -> DataFrame:
    """(start, end) of the walks of at least low (0 or 1) edges from seeds (start), where each edge is walked both ways.

    A walk leads to every node of the component, and back to its start over any edge.
    The starts of a component are dealt to blocks, so that a large one is many tasks.
    """
    labels = stored(components(edges).distinct(), "components")
    start = seeds.join(labels.withColumnRenamed("node", "start"), "start").withColumn("block", F.pmod(F.xxhash64("start"), F.lit(BLOCKS)))
    end = labels.withColumnRenamed("node", "end").withColumn("block", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(BLOCKS - 1).cast("long"))))
    pairs = start.repartition(BLOCKS * 2, "label", "block").join(end, ["label", "block"]).select("start", "end")
    if low:
        return pairs
    alone = seeds.join(labels.select(F.col("node").alias("start")), "start", "left_anti")
    return pairs.unionByName(alone.select("start", F.col("start").alias("end")))
