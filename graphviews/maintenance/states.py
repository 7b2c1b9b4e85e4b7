"""What the operators of a network keep between refreshes.

``Runs`` is a relation in parts, a base and changes, whose weights add up.  A grouping
keeps a row of partial aggregates a group, and counts of values where an aggregate is
not additive; a sort with a limit keeps its best rows and some spare ones.
"""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphviews.maintenance.changes import added, negated
from graphviews.operators.lowering import ADDITIVE, aggregate, order_of, sorted_top
from graphviews.plans.expr import Var, column, flat, to_column
from graphviews.plans.ops import Group, SortTop
from graphviews.sources.graph import WEIGHT, consolidated
from graphviews.sources.shared import Run, run_of

#: Changes of a relation before they are merged, and the share of the base from which they are merged into it.
MOST_RUNS, INTO_BASE = 4, 4


def touching(rows: DataFrame, touched: DataFrame, exprs: list[Column]) -> DataFrame:
    """Rows whose key is among the touched ones (_k0, _k1, ...); nulls are keys too."""
    if not exprs:
        return rows
    cond = reduce(lambda a, b: a & b, [e.eqNullSafe(F.col(f"_k{i}")) for i, e in enumerate(exprs)])
    return rows.join(touched, cond, "left_semi")


def among(rows: DataFrame, others: DataFrame, names: list[str], how: str = "left_semi") -> DataFrame:
    """Rows joined with others on columns of one name, nulls equal; without names every row meets every other."""
    if not names:
        return rows if how == "left_semi" else rows.crossJoin(others)
    others = others.withColumnsRenamed({n: f"_of{n}" for n in names})
    return rows.join(others, reduce(lambda a, b: a & b, [F.col(n).eqNullSafe(F.col(f"_of{n}")) for n in names]), how).drop(*[f"_of{n}" for n in names])


class Runs:
    """Parts whose weights add up, and one more while a refresh is on."""

    def __init__(self, label: str, folder: str | None = None, parts: list[Run] | None = None):
        self.label, self.folder, self.parts = label, folder, parts or []
        self.pending: Run | None = None

    def written(self, df: DataFrame) -> Run:
        return run_of(df, self.label, self.folder)

    def now(self, fresh: bool = False) -> DataFrame:
        return added([p.df for p in self.parts] + ([self.pending.df] if fresh and self.pending else []))

    def rows(self) -> int:
        return sum(p.rows for p in self.parts)

    def commit(self) -> list[Run]:
        """Take the pending part over; the runs that are no longer read."""
        if self.pending is None:
            return []
        self.parts, self.pending = [*self.parts, self.pending], None
        if len(self.parts) <= MOST_RUNS:
            return []
        base, tail = self.parts[0], self.parts[1:]
        gone = tail if sum(p.rows for p in tail) * INTO_BASE < base.rows else self.parts
        self.parts = [*([base] if gone is tail else []), self.written(consolidated(added([p.df for p in gone])))]
        return gone


class Table:
    """A base table: the relation it was at first, and its changes, merged when there are many."""

    def __init__(self, first: DataFrame, runs: Runs):
        self.first, self.runs = first, runs

    def now(self, fresh: bool = False) -> DataFrame:
        changed = self.runs.now(fresh)
        return self.first if changed is None else self.first.unionByName(changed)


class GroupState:
    """Partial aggregates by group.

    Counts, sums and what follows from them change by what the change adds up to.  A
    minimum or maximum moves with what comes in; only where the extreme value itself goes
    are the counts of values read, for those groups.  Other aggregates (collections,
    percentiles, distinct ones) are taken from the counts of values of touched groups.
    Sums of doubles are rounded in the order of the changes.
    """

    def __init__(self, op: Group, label: str, folder: str | None = None):
        self.op = op
        alias = {n: e.name for n, e in op.keys if isinstance(e, Var)}
        self.keys = [(n, to_column(e)) for n, e in op.keys] + [(flat(n, k), column(flat(alias[n], k))) for n, k in op.keep]
        self.names = [f"_k{i}" for i in range(len(self.keys))]
        self.kinds = ["additive" if a.name in ADDITIVE and not a.distinct else "extreme" if a.name in ("min", "max") else "valued" for _, a in op.outs]
        self.sums = ["_rows"]
        for i, (_, a) in enumerate(op.outs):
            if self.kinds[i] == "additive":
                self.sums += [f"_n{i}", *([f"_s{i}"] if a.name != "count" else []), *([f"_q{i}"] if a.name.startswith("stdev") else [])]
        self.finals = [f"_m{i}" for i, k in enumerate(self.kinds) if k != "additive"]
        self.partials = Runs(f"{label}-groups", folder)
        self.values = Runs(f"{label}-values", folder) if self.finals else None

    def valued(self, rows: DataFrame) -> DataFrame:
        """Keys and arguments of rows, with how often they stand; sums alone need no merged rows."""
        args = [to_column(a.arg).alias(f"_x{i}") for i, (_, a) in enumerate(self.op.outs) if a.arg is not None]
        found = rows.select(*[e.alias(n) for n, (_, e) in zip(self.names, self.keys)], *args, WEIGHT)
        return consolidated(found) if {*self.kinds} - {"additive"} or not self.kinds else found

    def summed(self, valued: DataFrame) -> DataFrame:
        """Sums by group, and the extremes that come and go."""
        w, made = F.col(WEIGHT), [F.coalesce(F.sum(WEIGHT), F.lit(0)).alias("_rows")]
        for i, (_, a) in enumerate(self.op.outs):
            x = F.col(f"_x{i}") if a.arg is not None else None
            if self.kinds[i] == "additive":
                known = F.when(x.isNotNull(), w).otherwise(0) if x is not None else w
                values = {"n": F.coalesce(F.sum(known), F.lit(0)), "s": F.coalesce(F.sum(x * w), F.lit(0)) if x is not None else None, "q": F.coalesce(F.sum((x * x * w).cast("double")), F.lit(0.0)) if x is not None else None}
                made += [values[c[1]].alias(c) for c in self.sums if c[2:] == str(i)]
            elif self.kinds[i] == "extreme":
                best = getattr(F, a.name)
                made += [best(F.when(w > 0, x)).alias(f"_in{i}"), best(F.when(w < 0, x)).alias(f"_out{i}")]
        return valued.groupBy(*self.names).agg(*made)

    def recomputed(self, values: DataFrame) -> DataFrame:
        """Keys and final values of the aggregates that are not additive."""
        made = [aggregate(replace(a, arg=Var(f"_x{i}")), True).alias(f"_m{i}") for i, (_, a) in enumerate(self.op.outs) if self.kinds[i] != "additive"]
        return consolidated(values, positive=True).groupBy(*self.names).agg(*made)

    def load(self, rows: DataFrame) -> None:
        valued = self.valued(rows)
        if self.values is None:
            made = self.summed(valued)
        else:
            self.values.parts = [self.values.written(valued)]
            valued = self.values.now()
            made = among(self.summed(valued).drop(*self._moves()), self.recomputed(valued), self.names, "left")
        made = made.where("_rows > 0") if self.names else made
        self.partials.parts = [self.partials.written(self._row(made))]

    def _moves(self) -> list[str]:
        return [f"_{side}{i}" for i, k in enumerate(self.kinds) if k == "extreme" for side in ("in", "out")]

    def _row(self, made: DataFrame) -> DataFrame:
        return made.select(*self.names, *self.sums, *self.finals).withColumn(WEIGHT, F.lit(1).cast("long"))

    def refresh(self, delta: DataFrame) -> DataFrame | None:
        """The signed change of the groups; partials and values wait for the commit."""
        valued = self.valued(delta)
        if self.values is not None:
            self.values.pending = self.values.written(valued)
            valued = self.values.pending.df
        change = self.summed(valued)
        if self.values is None:  # it is read twice, and what it is made of may be many rows
            change = run_of(change, f"{self.partials.label}-change").df
        held = consolidated(self.partials.now(), positive=True).drop(WEIGHT)
        old = among(held, change.select(*self.names), self.names)
        moves, nothing = self._moves(), F.lit(None)
        before = old.select("*", *[nothing.cast(change.schema[m].dataType).alias(m) for m in moves])
        after = change.select("*", *[nothing.cast(held.schema[m].dataType).alias(m) for m in self.finals])
        extreme = {f"_{side}{i}": getattr(F, self.op.outs[i][1].name) for i, k in enumerate(self.kinds) if k == "extreme" for side in ("m", "in", "out")}
        merged = before.unionByName(after).groupBy(*self.names).agg(
            *[F.sum(c).alias(c) for c in self.sums], *[extreme[c](c).alias(c) if c in extreme else F.first(c, True).alias(c) for c in (*self.finals, *moves)]
        )
        merged = merged.where("_rows > 0") if self.names else merged
        if self.finals:
            merged = self._settled(merged)
        run = self.partials.written(consolidated(self._row(merged).unionByName(negated(self._row(old)))))
        self.partials.pending = run if run.rows else None
        return self.final(run.df) if run.rows else None

    def _settled(self, merged: DataFrame) -> DataFrame:
        """Extremes moved by what came in; groups that lost theirs, or have other values, from the counts of values."""
        lost = F.lit("valued" in self.kinds)
        for i, (_, a) in enumerate(self.op.outs):
            if self.kinds[i] == "extreme":
                out, own = F.col(f"_out{i}"), F.col(f"_m{i}")
                lost = lost | F.coalesce(out >= own if a.name == "max" else out <= own, F.lit(False))
                moved = (F.greatest if a.name == "max" else F.least)(own, F.col(f"_in{i}"))
                merged = merged.withColumn(f"_moved{i}", moved)
        run = run_of(merged.withColumn("_lost", lost), f"{self.partials.label}-moved", mark=F.col("_lost"))
        marked = run.df
        moved = marked.where("not _lost").select(*self.names, *self.sums, *[F.col(f"_moved{c[2:]}").alias(c) if f"_moved{c[2:]}" in marked.columns else F.col(c) for c in self.finals])
        lost_ = marked.where("_lost")
        if not run.marked:
            return moved
        values = among(self.values.now(True), lost_.select(*self.names), self.names)
        again = among(lost_.select(*self.names, *self.sums), self.recomputed(values), self.names, "left")
        return moved.unionByName(again.select(*self.names, *self.sums, *self.finals))

    def final(self, partials: DataFrame) -> DataFrame:
        """Rows of the grouping from rows of partials, weights as they are."""
        made = [F.col(n).alias(name) for n, (name, _) in zip(self.names, self.keys)]
        for i, (name, a) in enumerate(self.op.outs):
            if self.kinds[i] != "additive":
                made.append(F.col(f"_m{i}").alias(name))
                continue
            n, s, q = (F.col(f"_{c}{i}") for c in "nsq")
            match a.name:
                case "count":
                    value = n.cast("long")
                case "sum":
                    value = F.when(n > 0, s)
                case "avg":
                    value = F.when(n > 0, s / n)
                case "stdev" | "stdevp":
                    over = n - 1 if a.name == "stdev" else n
                    value = F.when(over > 0, F.sqrt(F.greatest(q - s * s / n, F.lit(0.0)) / over))
            made.append(value.alias(name))
        count = len(self.op.keys)
        return partials.select(*made[:count], *made[len(self.keys) :], *made[count : len(self.keys)], WEIGHT)

    def relation(self, fresh: bool) -> DataFrame:
        return self.final(consolidated(self.partials.now(fresh), positive=True))

    def kept(self) -> dict[str, Runs]:
        return {"groups": self.partials, **({"values": self.values} if self.values else {})}


class TopState:
    """The best rows of a sort with a limit, and spare ones for deletes to eat.

    Rows beyond the last kept one are unknown, so what comes in there is left out; where
    the kept rows no longer fill the limit, they are taken anew from the rows below.
    """

    def __init__(self, op: SortTop, label: str, folder: str | None = None, spare: int = 50):
        self.op, self.wanted = op, op.skip + op.limit
        self.size = self.wanted + spare
        self.best = Runs(f"{label}-best", folder)
        self.refills = 0

    def _first(self, rows: DataFrame, n: int) -> DataFrame:
        return rows.orderBy(*order_of(self.op, rows)).limit(n)

    def _keep(self, rows: DataFrame) -> Run:
        # one row more than are kept tells whether these are all
        return self.best.written(self._first(rows, self.size + 1))

    def complete(self) -> bool:
        return self.best.parts[0].rows <= self.size

    def load(self, rows: DataFrame) -> None:
        self.best.parts = [self._keep(consolidated(rows, positive=True))]

    def refresh(self, delta: DataFrame, below) -> DataFrame | None:
        """The signed change of the result; below() gives all rows after the change."""
        delta = run_of(consolidated(delta), f"{self.best.label}-change").df
        old = self.best.parts[0].df
        names = [c for c in old.columns if c != WEIGHT]
        came = self._first(delta.where(F.col(WEIGHT) > 0), self.size + 1)
        gone = touching(delta.where(F.col(WEIGHT) < 0), F.broadcast(old.select(*[column(c).alias(f"_k{i}") for i, c in enumerate(names)])), [column(c) for c in names])
        marked = [part.withColumn("_kept", F.lit(k)) for part, k in ((old, 1), (came, 0), (gone, 0))]
        rows = added(marked).groupBy(*[column(c) for c in names]).agg(F.sum(WEIGHT).cast("long").alias(WEIGHT), F.max("_kept").alias("_kept"))
        if not self.complete():  # a window over the kept rows and as many of the change
            order = Window.orderBy(*order_of(self.op, old))
            rows = rows.withColumn("_known", F.max("_kept").over(order.rowsBetween(0, Window.unboundedFollowing))).where("_known = 1").drop("_known")
        kept = self._keep(rows.where(F.col(WEIGHT) > 0).drop("_kept"))
        if not self.complete() and kept.rows <= self.size:
            held = kept.df.agg(F.sum(WEIGHT)).first()[0] or 0
            if held < self.wanted:
                self.refills += 1
                kept = self._keep(consolidated(below(), positive=True))
            else:
                kept = Run(kept.df, self.size + 1, kept.path)  # fewer than before, but not all there are
        before = sorted_top(self.op, old)
        self.best.pending = kept
        return sorted_top(self.op, kept.df).unionByName(negated(before))

    def relation(self, fresh: bool) -> DataFrame:
        run = self.best.pending if fresh and self.best.pending else self.best.parts[0]
        return sorted_top(self.op, run.df)

    def commit(self) -> list[Run]:
        if self.best.pending is None:
            return []
        gone, self.best.parts, self.best.pending = self.best.parts, [self.best.pending], None
        return gone

    def kept(self) -> dict[str, Runs]:
        return {"best": self.best}
