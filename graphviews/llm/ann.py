"""Approximate nearest neighbours from low-dimensional stable projections in a kd-tree.

Vectors are projected to ``dims`` dimensions with normal (2-stable) weights, so a
squared projected distance over the squared true one has a chi-square law.  A
kd-tree holds the projections.  A query takes its projected neighbours one after the
other, nearest first, verifies them in full, and stops when the next one is so far
that, by the chi-square law, a vector nearer than the k found would lie within that
projected distance with probability ``confidence``.

The top of the tree is fitted to at most ``sample`` vectors and splits the space into
cells of about ``cell_rows``; every vector lies in one cell, which one task indexes.
A query first searches its own cell; the distance it has then decides which other
cells pass the stopping test, and only those see it.  Queries of a cell go in blocks.
How many vectors are verified depends on the data: fewer, the lower their true dimension;
in isotropic ones of 64 dimensions some 30 to 40 of 100, and no cell is out of reach.

Equal vectors are one point with its k+1 smallest ids (no answer can hold more of
them), and equal queries are searched once, so copies cost nothing.

Defined results: vectors that are null, zero or hold null or non-finite components
take no part; only vectors of equal length compare; ties go to the smaller id; fewer
candidates than k are all returned; a null id takes no part; repeated ids with
different vectors are different candidates.
"""

from __future__ import annotations

import heapq
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphviews.llm.common import stored, table

#: The fewer dimensions, the weaker the test: with 8 it never holds before the end on vectors whose tenth neighbour is three quarters as far as the median.
DIMS, CONFIDENCE = 24, 0.95
CELL_ROWS, LEAF, SAMPLE, QUERY_BLOCK = 16_384, 128, 20_000, 8192
#: Vectors verified at first before the test is asked again.
BLOCK = 32
SEED = 20240907


def projection(length: int, dims: int = DIMS) -> np.ndarray:
    return np.random.default_rng([SEED, length]).standard_normal((length, dims))


def chi_square_cdf(x: np.ndarray | float, dims: int):
    """For an even number of dimensions."""
    half = np.asarray(x, float) / 2
    term = total = np.ones_like(half)
    for i in range(1, dims // 2):
        term = term * half / i
        total = total + term
    return 1 - np.exp(-half) * total


def stop_ratio(confidence: float, dims: int) -> float:
    """Squared projected over squared true distance beyond which the test holds."""
    lo, hi = 0.0, 10.0 * dims + 100
    for _ in range(100):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if chi_square_cdf(mid, dims) < confidence else (lo, mid)
    return hi


class Splits:
    """A kd-tree's inner nodes: at each the axis and value; cells are numbered by their path."""

    def __init__(self, points: np.ndarray, depth: int):
        self.depth = depth
        self.axis = np.zeros((1 << depth) - 1, np.int64)
        self.value = np.zeros((1 << depth) - 1)
        groups = [points]
        for level in range(depth):
            following = []
            for k, p in enumerate(groups):
                node = (1 << level) - 1 + k
                if len(p):
                    self.axis[node] = axis = int(np.argmax(p.max(0) - p.min(0)))
                    self.value[node] = value = float(np.median(p[:, axis]))
                    following += [p[p[:, axis] < value], p[p[:, axis] >= value]]
                else:
                    following += [p, p]
            groups = following

    def cell(self, points: np.ndarray) -> np.ndarray:
        node = np.zeros(len(points), np.int64)
        for _ in range(self.depth):
            right = points[np.arange(len(points)), self.axis[node]] >= self.value[node]
            node = 2 * node + 1 + right
        return node - ((1 << self.depth) - 1)

    def within(self, point: np.ndarray, reach: float) -> list[int]:
        """Cells at a squared distance of at most reach from the point."""
        out, todo = [], [(0, np.zeros(len(point)))]
        inner = (1 << self.depth) - 1
        while todo:
            node, gaps = todo.pop()
            if node >= inner:
                out.append(node - inner)
                continue
            axis, off = self.axis[node], point[self.axis[node]] - self.value[node]
            near, far = (2 * node + 2, 2 * node + 1) if off >= 0 else (2 * node + 1, 2 * node + 2)
            todo.append((near, gaps))
            beyond = gaps.copy()
            beyond[axis] = max(beyond[axis], off * off)
            if beyond.sum() <= reach:
                todo.append((far, beyond))
        return out


class Tree:
    """kd-tree of a cell's projections: leaves with their boxes, their rows side by side, and the true vectors."""

    def __init__(self, vectors: np.ndarray, projected: np.ndarray):
        todo, leaves = [np.arange(len(vectors))], []
        while todo:
            rows = todo.pop()
            if len(rows) <= LEAF:
                leaves.append(rows)
                continue
            part = projected[rows]
            split = np.argpartition(part[:, int(np.argmax(part.max(0) - part.min(0)))], len(rows) // 2)
            todo += [rows[split[len(rows) // 2 :]], rows[split[: len(rows) // 2]]]
        self.rows = np.concatenate(leaves)
        self.begin = np.cumsum([0, *map(len, leaves)])
        self.vectors, self.projected = vectors[self.rows], projected[self.rows]
        self.low = np.array([self.projected[a:b].min(0) for a, b in zip(self.begin, self.begin[1:])])
        self.high = np.array([self.projected[a:b].max(0) for a, b in zip(self.begin, self.begin[1:])])

    def search(self, vector: np.ndarray, point: np.ndarray, counts: np.ndarray, wanted: int, ratio: float, worst: float) -> tuple[list[int], list[float], float, int]:
        """Rows and distances that may be among the wanted nearest, the distance that holds them, and how many vectors were verified.

        Leaves are opened in the order of their boxes' distance, some more each time.  What lies
        nearer than the next box is verified in the order of its projected distance, in blocks,
        until the test holds for the next one.
        """
        off = np.maximum(np.maximum(self.low - point, point - self.high), 0)
        gaps = np.einsum("ij,ij->i", off, off)
        leaves = np.argsort(gaps, kind="stable")
        gaps = gaps[leaves]
        rows, dist, verified = np.zeros(0, np.int64), np.zeros(0), 0
        waiting, ahead = np.zeros(0, np.int64), np.zeros(0)
        at, some = 0, 4
        while at < len(leaves) and gaps[at] <= ratio * worst * worst:
            opened = leaves[at : at + some]
            at, some = at + some, 2 * some
            new = np.concatenate([np.arange(self.begin[x], self.begin[x + 1]) for x in opened.tolist()])
            away = self.projected[new] - point
            away = np.einsum("ij,ij->i", away, away)
            near = away <= ratio * worst * worst
            waiting, ahead = np.concatenate([waiting, new[near]]), np.concatenate([ahead, away[near]])
            order = np.argsort(ahead, kind="stable")
            waiting, ahead = waiting[order], ahead[order]
            sure = int(np.searchsorted(ahead, gaps[at], "right")) if at < len(leaves) else len(ahead)
            lo, block = 0, BLOCK
            while lo < sure and ahead[lo] <= ratio * worst * worst:
                hi = min(sure, lo + block, int(np.searchsorted(ahead, ratio * worst * worst, "right")))
                off = self.vectors[waiting[lo:hi]] - vector
                verified += hi - lo
                off = np.sqrt((off * off).sum(1))
                near = off <= worst
                rows = np.concatenate([rows, self.rows[waiting[lo:hi][near]]])
                dist = np.concatenate([dist, off[near]])
                order = np.argsort(dist, kind="stable")
                rows, dist = rows[order], dist[order]
                enough = int(np.searchsorted(np.cumsum(counts[rows]), wanted))
                if enough < len(rows):
                    worst = min(worst, float(dist[enough]))
                    keep = int(np.searchsorted(dist, worst, "right"))
                    rows, dist = rows[:keep], dist[:keep]
                lo, block = hi, min(2 * block, 32 * BLOCK)
            if lo < sure:
                break  # the test holds for all that lies farther
            waiting, ahead = waiting[sure:], ahead[sure:]
        near = dist <= worst
        return rows[near].tolist(), dist[near].tolist(), worst, verified


def _matrix(column: pa.ChunkedArray, length: int) -> np.ndarray:
    flat = column.combine_chunks()
    flat = flat.flatten() if not isinstance(flat, pa.ChunkedArray) else pa.concat_arrays([c.flatten() for c in flat.chunks])
    return flat.to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, length)


def _cell_search(splits_of, wanted: int, confidence: float, dims: int, first: bool):
    ratio = stop_ratio(confidence, dims)

    def run(group: pa.Table) -> pa.Table:
        length = group.column("length")[0].as_py()
        matrix = projection(length, dims)
        ask = np.array(group.column("ask").to_pylist(), bool)
        point = np.array(group.column("point").to_pylist(), bool)
        vectors = _matrix(group.column("v"), length)
        projected = vectors @ matrix
        out = {"key": [], "ids": [], "scores": [], "worst": [], "cells": [], "verified": []}
        keys, worst = group.column("key").to_pylist(), group.column("worst").to_pylist()
        ids = [x for x, p in zip(group.column("ids").to_pylist(), point) if p]
        tree = Tree(vectors[point], projected[point]) if len(ids) else None
        counts = np.fromiter(map(len, ids), np.int64, len(ids))
        splits = splits_of().get(length) if first else None
        own = group.column("cell")[0].as_py()
        for q in np.flatnonzero(ask).tolist():
            rows, dist, limit, verified = tree.search(vectors[q], projected[q], counts, wanted, ratio, worst[q] if worst[q] is not None else math.inf) if tree else ([], [], math.inf, 0)
            found = sorted((d, i) for r, d in zip(rows, dist) for i in ids[r])[:wanted]
            out["key"].append(keys[q])
            out["ids"].append([i for _, i in found])
            out["scores"].append([d for d, _ in found])
            out["worst"].append(limit)
            out["verified"].append(verified)
            out["cells"].append([c for c in splits.within(projected[q], ratio * limit * limit) if c != own] if first and splits else [])
        return pa.table({"key": pa.array(out["key"], pa.binary()), "ids": pa.array(out["ids"], pa.list_(pa.int64())), "scores": pa.array(out["scores"], pa.list_(pa.float64())),
                         "worst": pa.array(out["worst"], pa.float64()), "cells": pa.array(out["cells"], pa.list_(pa.int64())), "verified": pa.array(out["verified"], pa.int64())})

    return run


def nearest(points: DataFrame, queries: DataFrame, *, k: int = 10, vec_id: str = "vec_id", embedding: str = "embedding", dims: int = DIMS, confidence: float = CONFIDENCE, cell_rows: int = CELL_ROWS, sample: int = SAMPLE) -> DataFrame:
    """The k nearest points of each query row but its own id: query_id, rank, vec_id, score, verified (vectors compared in full)."""
    spark = points.sparkSession

    def valid(df: DataFrame) -> DataFrame:
        v = F.col(embedding).cast("array<double>")
        bad = F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
        rows = df.select(F.col(vec_id).cast("long").alias("id"), v.alias("v")).where(F.col("id").isNotNull() & F.col("v").isNotNull())
        rows = rows.where(~bad & F.exists("v", lambda x: x != 0))
        rows = rows.withColumn("v", F.transform("v", lambda x: F.when(x == 0, F.lit(0.0)).otherwise(x)))
        return rows.withColumn("key", F.unhex(F.md5(F.concat_ws(",", F.transform("v", lambda x: x.cast("string")))))).select("id", "v", "key")

    asked = valid(queries)
    rank = F.row_number().over(Window.partitionBy("key").orderBy("id"))
    few = valid(points).withColumn("r", rank).where(F.col("r") <= k + 1)
    distinct = few.groupBy("key").agg(F.first("v").alias("v"), F.sort_array(F.collect_list("id")).alias("ids"))
    asking = asked.groupBy("key").agg(F.first("v").alias("qv"))
    both = distinct.join(asking, "key", "full").select(
        "key", F.coalesce("v", "qv").alias("v"), "ids", F.col("ids").isNotNull().alias("point"), F.col("qv").isNotNull().alias("ask")
    )
    both = stored(both.withColumn("length", F.size("v")), "vectors")
    counts = {r["length"]: r["n"] for r in both.where("point").groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}
    # lengths of more than a cell share the sample; the others are one cell each
    large = {length: n for length, n in counts.items() if n > cell_rows}
    splits: dict[int, Splits] = {}
    if large:
        first = F.row_number().over(Window.partitionBy("length").orderBy("key"))
        picked = both.where("point").where(F.col("length").isin(list(large))).withColumn("r", first).where(F.col("r") <= max(1, sample // len(large)))
        by_length: dict[int, list] = {}
        for r in picked.select("length", "v").collect():  # at most the sample
            by_length.setdefault(r["length"], []).append(r["v"])
        for length, vectors in by_length.items():
            depth = math.ceil(math.log2(large[length] / cell_rows))
            splits[length] = Splits(np.array(vectors) @ projection(length, dims), depth)
    shared = spark.sparkContext.broadcast(splits)

    def assign(batches):
        for batch in batches:
            lengths = batch.column("length").to_numpy()
            cell = np.zeros(len(batch), np.int64)
            for length in np.unique(lengths).tolist():
                rows = np.flatnonzero(lengths == length)
                if length in shared.value:
                    v = np.array(batch.column("v").take(pa.array(rows)).to_pylist(), float)
                    cell[rows] = shared.value[length].cell(v @ projection(length, dims))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(cell)], [*batch.schema.names, "cell"])

    placed = both.mapInArrow(assign, "key binary, v array<double>, ids array<long>, point boolean, ask boolean, length int, cell long")
    result = "key binary, ids array<long>, scores array<double>, worst double, cells array<long>, verified long"
    home = placed.withColumn("worst", F.lit(None).cast("double")).groupBy("length", "cell")
    first = stored(home.applyInArrow(_cell_search(lambda: shared.value, k + 1, confidence, dims, True), result), "home")
    more = first.select("key", "worst", F.explode("cells").alias("cell")).join(both.select("key", "v", "length"), "key")
    visits = more.groupBy("length", "cell").agg(F.ceil(F.count(F.lit(1)) / QUERY_BLOCK).cast("int").alias("blocks"))
    guests = more.join(visits, ["length", "cell"]).select(
        "key", "v", F.lit(None).cast("array<bigint>").alias("ids"), F.lit(False).alias("point"), F.lit(True).alias("ask"), "length", "cell", "worst",
        F.pmod(F.xxhash64("key", "cell"), "blocks").cast("int").alias("block"),
    )
    hosts = placed.where("point").join(visits, ["length", "cell"]).select(
        "key", "v", "ids", "point", F.lit(False).alias("ask"), "length", "cell", F.lit(None).cast("double").alias("worst"),
        F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"),
    )
    second = guests.unionByName(hosts).groupBy("length", "cell", "block").applyInArrow(_cell_search(lambda: shared.value, k + 1, confidence, dims, False), result)
    searched = first.unionByName(second)
    work = searched.groupBy("key").agg(F.sum("verified").alias("verified"))
    found = searched.select("key", F.explode(F.arrays_zip("ids", "scores")).alias("x"))
    found = found.select("key", F.col("x.ids").alias("vec_id"), F.col("x.scores").alias("score"))
    best = found.withColumn("r", F.row_number().over(Window.partitionBy("key").orderBy("score", "vec_id"))).where(F.col("r") <= k + 1).drop("r")
    per_query = asked.select(F.col("id").alias("query_id"), "key").join(best, "key").where("vec_id <> query_id")
    order = Window.partitionBy("query_id", "key").orderBy("score", "vec_id")
    return per_query.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).join(work, "key").select("query_id", "rank", "vec_id", "score", "verified")


def op3_nearest_neighbours(spark, sf_dir):
    points = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return nearest(points, points.where("vec_id % 100 = 0")).drop("verified")
