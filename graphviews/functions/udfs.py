"""Python functions, only where built-in ones have no form for them; all take Arrow batches."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from graphviews.sources.shared import run_of, stored

#: Rows of a hierarchy that one task may hold and the plan may broadcast.
HIERARCHY_LIMIT = 1_000_000


@F.pandas_udf(T.DoubleType())
def bag_median(values: pd.Series) -> float:
    """Median of a bag; null where it is empty."""
    values = values.dropna()
    return float(values.median()) if len(values) else None


def ancestors(spark: SparkSession, nodes: DataFrame, parents: DataFrame, most: int = HIERARCHY_LIMIT) -> DataFrame:
    """(node, ancestor, hops) of nodes (node) over a hierarchy (child, parent), expanded inside tasks.

    The hierarchy is broadcast, so its size is checked; one of more than ``most`` edges is
    cut into blocks of keys, and rows whose ancestor lies in another block go on there.
    """
    n = parents.count()
    if n > most:
        return _ancestors_by_blocks(nodes, parents, -(-n // most) * 2)
    up = spark.sparkContext.broadcast({r["child"]: r["parent"] for r in parents.toLocalIterator()})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parent = up.value
        for batch in batches:
            rows = []
            for node in batch.column(0).to_pylist():
                at, hops = parent.get(node), 1
                while at is not None:
                    rows.append((node, at, hops))
                    at, hops = parent.get(at), hops + 1
            columns = list(zip(*rows)) or [(), (), ()]
            yield pa.RecordBatch.from_arrays([pa.array(columns[0], pa.int64()), pa.array(columns[1], pa.int64()), pa.array(columns[2], pa.int32())], ["node", "ancestor", "hops"])

    return nodes.select(F.col("node").cast("long")).mapInArrow(run, "node long, ancestor long, hops int")


def _ancestors_by_blocks(nodes: DataFrame, parents: DataFrame, blocks: int) -> DataFrame:
    """The same where no task may hold the whole hierarchy: a task holds a block and walks up inside it.

    Rounds end when no walk goes on; a walk leaves a block at most once for every edge between blocks on its way.
    """
    block = lambda c: F.pmod(F.xxhash64(F.col(c).cast("long")), F.lit(blocks))
    held = stored(parents.select(F.col("child").cast("long"), F.col("parent").cast("long")).withColumn("block", block("child")), "hierarchy")
    front, found = nodes.select(F.col("node").cast("long"), F.col("node").cast("long").alias("at"), F.lit(0).alias("hops")), []

    def walk(walks: pa.Table, edges: pa.Table) -> pa.Table:
        parent = dict(zip(edges.column("child").to_pylist(), edges.column("parent").to_pylist()))
        rows = []
        for node, at, hops in zip(*(walks.column(c).to_pylist() for c in ("node", "at", "hops"))):
            while (at := parent.get(at)) is not None:
                hops += 1
                rows.append((node, at, hops, at not in parent))
        columns = list(zip(*rows)) or [(), (), (), ()]
        return pa.table([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int64(), pa.int32(), pa.bool_()))], ["node", "at", "hops", "last"])

    while True:
        step = front.withColumn("block", block("at")).groupBy("block").cogroup(held.groupBy("block")).applyInArrow(walk, "node long, at long, hops int, last boolean")
        run = run_of(step, "ancestors")
        if not run.rows:
            break
        found.append(run.df)
        front = run.df.where("last").select("node", "at", "hops")
    rows = reduce(DataFrame.unionByName, found) if found else front.where("false")
    return rows.select("node", F.col("at").alias("ancestor"), "hops")


def keyed_outer_change(left: DataFrame, right: DataFrame, change: DataFrame, key: str) -> DataFrame:
    """Signed change of a left outer join (left and right by key) under signed rows of right, key by key.

    left (key, l), right (key, r), change (key, r, w); result (key, l, r, w).
    """
    touched = change.select(key).distinct()
    rows = left.join(touched, key, "left_semi").withColumns({"side": F.lit("l"), "r": F.lit(None).cast("long"), "w": F.lit(1).cast("long")})
    old = right.join(touched, key, "left_semi").withColumns({"side": F.lit("r"), "l": F.lit(None).cast("long"), "w": F.lit(1).cast("long")})
    new = change.withColumns({"side": F.lit("d"), "l": F.lit(None).cast("long"), "w": F.col("w").cast("long")})
    columns = [key, "side", "l", "r", "w"]

    def run(lefts: pd.DataFrame, others: pd.DataFrame) -> pd.DataFrame:
        if lefts.empty:
            return pd.DataFrame({key: [], "l": [], "r": [], "w": []}).astype({key: "int64", "l": "int64", "w": "int64"})
        before = others[others.side == "r"].groupby("r").w.sum()
        delta = others[others.side == "d"].groupby("r").w.sum()
        after = before.add(delta, fill_value=0)
        out = [(k, x, r, int(w)) for k, x in zip(lefts[key], lefts.l) for r, w in delta.items() if w]
        had, has = bool((before > 0).any()), bool((after > 0).any())
        if had != has:
            out += [(k, x, None, 1 if had else -1) for k, x in zip(lefts[key], lefts.l)]
        frame = pd.DataFrame(out, columns=[key, "l", "r", "w"])
        frame["r"] = frame["r"].astype("Int64")
        return frame

    sides = rows.select(columns).groupBy(key).cogroup(old.select(columns).unionByName(new.select(columns)).groupBy(key))
    return sides.applyInPandas(run, f"{key} long, l long, r long, w long")
