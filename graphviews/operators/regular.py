"""Regular path queries: a frontier that carries the state of an automaton over edge types."""

from __future__ import annotations

import re
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphviews.plans.expr import PlanError
from graphviews.sources.shared import run_of, stored

_PART = re.compile(r"\s*(\^?[A-Za-z_]\w*|[()|*+?/])")


def automaton(pattern: str) -> tuple[list[tuple[int, str, int]], int, set[int]]:
    """(transitions, start, ends) of a pattern of edge types with / for sequence, |, *, +, ? and ^ for backwards."""
    words, at = [], 0
    pattern = pattern.rstrip()
    while at < len(pattern):
        m = _PART.match(pattern, at)
        if not m:
            raise PlanError(f"cannot read {pattern[at:]!r}")
        words.append(m[1])
        at = m.end()
    steps: list[tuple[int, str | None, int]] = []
    count = 0

    def state() -> int:
        nonlocal count
        count += 1
        return count - 1

    def alternatives():
        a, b = state(), state()
        while True:
            s, e = sequence()
            steps.extend([(a, None, s), (e, None, b)])
            if not (words and words[0] == "|"):
                return a, b
            words.pop(0)

    def sequence():
        first, last = repeated()
        while words and words[0] == "/":
            words.pop(0)
            s, e = repeated()
            steps.append((last, None, s))
            last = e
        return first, last

    def repeated():
        if not words:
            raise PlanError("a pattern ends too early")
        word = words.pop(0)
        if word == "(":
            a, b = alternatives()
            if not words or words.pop(0) != ")":
                raise PlanError("missing )")
        elif word in ")|*+?/":
            raise PlanError(f"unexpected {word}")
        else:
            a, b = state(), state()
            steps.append((a, word, b))
        while words and words[0] in "*+?":
            sign, s, e = words.pop(0), state(), state()
            steps.extend([(s, None, a), (b, None, e)])
            if sign in "*?":
                steps.append((s, None, e))
            if sign in "*+":
                steps.append((b, None, a))
            a, b = s, e
        return a, b

    start, end = alternatives()
    if words:
        raise PlanError(f"unexpected {words[0]}")
    silent: dict[int, set[int]] = {}
    for s in range(count):
        seen, todo = {s}, [s]
        while todo:
            x = todo.pop()
            for a, word, b in steps:
                if a == x and word is None and b not in seen:
                    seen.add(b)
                    todo.append(b)
        silent[s] = seen
    moves = sorted({(s, word, b) for s in range(count) for x in silent[s] for a, word, b in steps if a == x and word is not None})
    return moves, start, {s for s in range(count) if end in silent[s]}


def regular_paths(spark: SparkSession, seeds: DataFrame, edges: DataFrame, pattern: str) -> DataFrame:
    """(start, end) pairs joined by a path whose edge types match the pattern; seeds (start), edges (type, s, t)."""
    moves, first, ends = automaton(pattern)
    turned = edges.select(F.concat(F.lit("^"), "type").alias("type"), F.col("t").alias("s"), F.col("s").alias("t"))
    used = sorted({w for _, w, _ in moves})
    both = stored(edges.select("type", "s", "t").unionByName(turned).where(F.col("type").isin(used)).distinct(), "typed")
    table = spark.createDataFrame(moves, "q long, type string, q2 long")
    front = stored(seeds.select("start", F.col("start").alias("end"), F.lit(first).cast("long").alias("q")).distinct(), "front")
    seen = [front]
    while True:
        step = front.join(F.broadcast(table), "q").join(both, (F.col("end") == F.col("s")) & (both["type"] == table["type"]))
        step = step.select("start", F.col("t").alias("end"), F.col("q2").alias("q")).distinct()
        run = run_of(step.join(reduce(DataFrame.unionByName, seen), ["start", "end", "q"], "left_anti"), "front")
        front = run.df
        if not run.rows:
            break
        seen.append(front)
    return reduce(DataFrame.unionByName, seen).where(F.col("q").isin(*sorted(ends))).select("start", "end").distinct()
