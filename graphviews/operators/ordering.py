"""Numbers and neighbours in a global order, without one task that sees all rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphviews.sources.shared import stored


def ranged(df: DataFrame, by: list[Column]) -> DataFrame:
    """df dealt to ranges of the order: _part numbers them, smaller numbers hold smaller rows."""
    return stored(df.repartitionByRange(*by).withColumn("_part", F.spark_partition_id()), "ranged")


def numbered(df: DataFrame, by: list[Column], name: str) -> DataFrame:
    """df with each row's place in the order, from 1: its place in its range, and the sizes of the ranges before."""
    parts = ranged(df, by)
    sizes = parts.groupBy("_part").agg(F.count(F.lit(1)).alias("n")).orderBy("_part").collect()  # a row a range
    before, rows = 0, []
    for r in sizes:
        rows.append((r["_part"], before))
        before += r["n"]
    offsets = df.sparkSession.createDataFrame(rows, "_part int, _before long")
    inside = F.row_number().over(Window.partitionBy("_part").orderBy(*by))
    return parts.withColumn("_in", inside).join(F.broadcast(offsets), "_part").withColumn(name, F.col("_in") + F.col("_before")).drop("_part", "_in", "_before")


def between(df: DataFrame, by: list[Column], key: str) -> DataFrame:
    """df with _low and _high: the last key at or before each row in the order, and the first at or after it; key is null where a row has none."""
    parts = ranged(df, by)
    ends = parts.groupBy("_part").agg(F.min(key).alias("low"), F.max(key).alias("high")).orderBy("_part").collect()  # a row a range
    last, lows = None, []
    for r in ends:
        lows.append(last)
        last = r["high"] if r["high"] is not None else last
    first, highs = None, []
    for r in reversed(ends):
        highs.append(first)
        first = r["low"] if r["low"] is not None else first
    rows = [(r["_part"], a, b) for r, a, b in zip(ends, lows, reversed(highs))]
    around = df.sparkSession.createDataFrame(rows, f"_part int, _from {dict(df.dtypes)[key]}, _to {dict(df.dtypes)[key]}")
    w = Window.partitionBy("_part").orderBy(*by)
    # a frame up to the end of the range would be read anew for every row; the next known key is one pass
    following = F.expr(f"lead(`{key}`) ignore nulls").over(w)
    inside = {"_low": F.last(key, True).over(w.rowsBetween(Window.unboundedPreceding, 0)), "_high": F.coalesce(F.col(key), following)}
    out = parts.withColumns(inside).join(F.broadcast(around), "_part")
    return out.withColumns({"_low": F.coalesce("_low", "_from"), "_high": F.coalesce("_high", "_to")}).drop("_part", "_from", "_to")
