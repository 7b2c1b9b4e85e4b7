"""Transitive joins: paths of bounded or unbounded length from the rows at hand.

Only vertices that occur in the left input are expanded.  Short bounded walks are
unrolled joins in one plan.  Others go hop by hop; each frontier is written to the
shared folder, so lineage stays short and an empty frontier ends the loop.

Modes: ``trail`` uses no edge twice, ``walk`` may (bounded only), ``reach`` gives each
end of a walk once and no path (so walking an edge there and back is a way home).  Indexes count along edge direction, so the path of an
incoming walk is turned round.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphviews.operators.components import reached
from graphviews.plans.expr import PlanError, column
from graphviews.plans.ops import BOTH, IN, TransitiveJoin
from graphviews.sources.graph import WEIGHT, consolidated, weighted_join
from graphviews.sources.shared import dropped, run_of, stored

UNROLLED = 3
STEP = "array<struct<edge:bigint,src:bigint,trg:bigint>>"


def expand(seeds: DataFrame, edges: DataFrame, low: int, up: int | None, mode: str, keep_path: bool = True, unrolled: int = UNROLLED) -> DataFrame:
    """(start, end, steps) of the paths of low to up edges (s, t, e) from the seeds (start)."""
    if mode == "walk" and up is None:
        raise PlanError("walks need an upper bound")
    front = seeds.select("start", F.col("start").alias("end"), F.array().cast(STEP).alias("steps"))
    hops = [front] if low == 0 else []
    edges = edges.select("s", "t", "e")
    if up is not None and up <= unrolled and mode != "reach":
        return _unrolled(front, edges, low, up, mode)
    edges = stored(edges, "edges")
    seen = front.select("start", "end") if low == 0 else None
    k = 0
    while up is None or k < up:
        k += 1
        step = front.join(edges, F.col("end") == F.col("s"))
        if mode == "trail":
            step = step.where(~F.exists("steps", lambda x: (x["edge"] == F.col("e")) & (_ends(x["src"], x["trg"]) == _ends(F.col("s"), F.col("t")))))
        grown = F.concat("steps", F.array(F.struct(F.col("e").alias("edge"), F.col("s").alias("src"), F.col("t").alias("trg")))) if keep_path and mode != "reach" else F.col("steps")
        front = step.select("start", F.col("t").alias("end"), grown.alias("steps"))
        if mode == "reach":
            front = front.dropDuplicates(["start", "end"])
            # ends of fewer hops than low are no answers yet: longer walks may come back to them
            if seen is not None and k >= low:
                front = front.join(seen, ["start", "end"], "left_anti").select("start", "end", "steps")
        run = run_of(front, "hop")
        front = run.df
        if not run.rows:
            break
        if k >= low:
            hops.append(front)
            if mode == "reach":
                ends = front.select("start", "end")
                seen = ends if seen is None else seen.unionByName(ends)
    if not hops:
        return front.limit(0)
    return reduce(DataFrame.unionByName, hops)


def _ends(a, b):
    """The two ends of an edge, in no direction."""
    return F.struct(F.least(a, b), F.greatest(a, b))


def _unrolled(front: DataFrame, edges: DataFrame, low: int, up: int, mode: str) -> DataFrame:
    """Paths as one plan: a hop's edge is three columns, and where no one reads the steps Spark drops the arrays."""
    front, hops = front.select("start", "end"), []
    for k in range(up + 1):
        if k:
            new = [f"_s{k}", f"_t{k}", f"_e{k}"]
            step = front.join(edges.toDF(*new), F.col("end") == F.col(f"_s{k}"))
            for j in range(1, k) if mode == "trail" else ():
                step = step.where((F.col(f"_e{j}") != F.col(f"_e{k}")) | (_ends(F.col(f"_s{j}"), F.col(f"_t{j}")) != _ends(F.col(f"_s{k}"), F.col(f"_t{k}"))))
            front = step.select("start", F.col(f"_t{k}").alias("end"), *[f"_{c}{j}" for j in range(1, k + 1) for c in "ste"])
        if k >= low:
            steps = [F.struct(F.col(f"_e{j}").alias("edge"), F.col(f"_s{j}").alias("src"), F.col(f"_t{j}").alias("trg")) for j in range(1, k + 1)]
            hops.append(front.select("start", "end", F.array(*steps).cast(STEP).alias("steps")))
    return reduce(DataFrame.unionByName, hops)


def indexed(steps, direction: str):
    """Steps as (index from 1, edge, src, trg) along edge direction."""
    turned = F.reverse(steps) if direction == IN else steps
    src, trg = ("trg", "src") if direction == IN else ("src", "trg")
    return F.transform(turned, lambda x, i: F.struct((i + 1).cast("int").alias("index"), x["edge"].alias("edge"), x[src].alias("src"), x[trg].alias("trg")))


def edge_pairs(scan: DataFrame, node: TransitiveJoin) -> DataFrame:
    """An edge scan as (s, t, e) in walking direction; weighted scans merge to the edges that are there.

    A loop that is walked both ways is there twice, in either form.
    """
    e = node.edges
    df = scan.select(column(e.v).alias("s"), column(e.w).alias("t"), column(e.e).alias("e"), *([WEIGHT] if WEIGHT in scan.columns else []))
    if WEIGHT not in df.columns:
        return df
    there = consolidated(df, positive=True)
    return there.withColumn("_n", F.explode(F.sequence(F.lit(1).cast("long"), F.col(WEIGHT)))).select("s", "t", "e")


def transitive_join(node: TransitiveJoin, left: DataFrame, scan: DataFrame, ends: DataFrame | None = None) -> DataFrame:
    """Rows of left with each path from v: its edge list and end; with ends, the paths to those alone, found from there."""
    edges = edge_pairs(scan, node)
    if ends is None:
        seeds = left.select(column(node.v).alias("start")).where("start is not null").distinct()
        if node.mode == "reach" and node.up is None and node.low <= 1 and node.direction == BOTH:
            found = reached(seeds, edges, node.low).withColumn("steps", F.array().cast(STEP))
        else:
            found = expand(seeds, edges, node.low, node.up, node.mode)
    else:
        seeds = ends.select(column(node.w).alias("start")).distinct()
        back = expand(seeds, edges.select(F.col("t").alias("s"), F.col("s").alias("t"), "e"), node.low, node.up, node.mode)
        turned = F.transform(F.reverse("steps"), lambda x: F.struct(x["edge"].alias("edge"), x["trg"].alias("src"), x["src"].alias("trg")))
        found = back.select(F.col("end").alias("start"), F.col("start").alias("end"), turned.alias("steps"))
    paths = found.select(F.col("start").alias(node.v), indexed(F.col("steps"), node.direction).alias(node.e), F.col("end").alias(node.w))
    return weighted_join(left, paths, [node.v])


def shortest(edges: DataFrame, sources: DataFrame, most: int | None = None) -> DataFrame:
    """(start, end, hops): fewest edges (s, t, e) from each source (start) to each vertex it reaches."""
    front = stored(sources.select("start", F.col("start").alias("end")).distinct(), "front")
    edges = stored(edges.select("s", "t").distinct(), "edges")
    levels, k = [front.withColumn("hops", F.lit(0))], 0
    while most is None or k < most:
        k += 1
        seen = reduce(DataFrame.unionByName, [x.select("start", "end") for x in levels])
        step = front.join(edges, F.col("end") == F.col("s")).select("start", F.col("t").alias("end")).distinct()
        run = run_of(step.join(seen, ["start", "end"], "left_anti"), "front")
        front = run.df
        if not run.rows:
            break
        levels.append(front.withColumn("hops", F.lit(k)))
    return reduce(DataFrame.unionByName, levels)


def doubled(edges: DataFrame) -> DataFrame:
    """Reachable pairs (s, t) over one or more edges, by squaring: as many rounds as the longest distance has bits."""
    first = run_of(edges.select("s", "t").distinct(), "pairs")
    pairs, n = first.df, first.rows
    while True:
        longer = pairs.alias("a").join(pairs.alias("b"), F.col("a.t") == F.col("b.s")).select("a.s", "b.t")
        run = run_of(pairs.unionByName(longer).distinct(), "pairs")
        following, more = run.df, run.rows
        dropped(pairs)
        if more == n:
            return following
        pairs, n = following, more
