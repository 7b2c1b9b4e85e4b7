"""Change sets: rows of base tables with a signed weight."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphviews.sources.graph import WEIGHT, consolidated


def weighted(df: DataFrame, weight: int = 1) -> DataFrame:
    return df if WEIGHT in df.columns else df.withColumn(WEIGHT, F.lit(weight).cast("long"))


def negated(df: DataFrame) -> DataFrame:
    return df.withColumn(WEIGHT, -F.col(WEIGHT))


def added(parts: list[DataFrame]) -> DataFrame | None:
    parts = [p for p in parts if p is not None]
    return reduce(DataFrame.unionByName, parts) if parts else None


class ChangeSet:
    """Inserted (weight 1) and deleted (weight -1) rows by table."""

    def __init__(self, tables: dict[str, DataFrame]):
        self.tables = {t: weighted(df) for t, df in tables.items()}

    @classmethod
    def inserts(cls, **tables: DataFrame) -> ChangeSet:
        return cls(tables)

    @classmethod
    def deletes(cls, **tables: DataFrame) -> ChangeSet:
        return cls({t: weighted(df, -1) for t, df in tables.items()})

    @classmethod
    def updates(cls, table: str, old: DataFrame, new: DataFrame) -> ChangeSet:
        return cls({table: weighted(old, -1).unionByName(weighted(new))})

    def __add__(self, other: ChangeSet) -> ChangeSet:
        names = {*self.tables, *other.tables}
        return ChangeSet({t: added([self.tables.get(t), other.tables.get(t)]) for t in names})

    def negate(self) -> ChangeSet:
        return ChangeSet({t: negated(df) for t, df in self.tables.items()})

    def consolidate(self) -> ChangeSet:
        return ChangeSet({t: consolidated(df) for t, df in self.tables.items()})

    def split(self, n: int) -> list[ChangeSet]:
        """n change sets that add up to this one, rows dealt by their hash."""
        return [ChangeSet({t: df.where(F.pmod(F.xxhash64(*df.columns), F.lit(n)) == i) for t, df in self.tables.items()}) for i in range(n)]
