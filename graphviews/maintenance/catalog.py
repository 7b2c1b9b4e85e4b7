"""Views by name over one graph, in memory or in a folder that outlives the session.

A view is refreshed at once, or *deferred*: its changes wait until it is read or
flushed, or *recomputed* whenever it is read.  With a folder, every commit writes a
manifest of all views, their states, the changes of the base tables and the batch
names seen; ``ViewCatalog.open`` goes on from the newest one.
"""

from __future__ import annotations

import json
import re
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphviews.maintenance.changes import ChangeSet
from graphviews.maintenance.network import HISTORY, Network, RefreshReport, base_tables, staged
from graphviews.maintenance.states import Runs, Table
from graphviews.plans.expr import PlanError
from graphviews.plans.ops import ScanEdges, ScanVertices
from graphviews.plans.rewrite import Options, Plans
from graphviews.sources.graph import PropertyGraph, inputs_of
from graphviews.sources.shared import Run, files, removed

POLICIES = ("immediate", "deferred", "recomputed")


class View:
    """A query whose result is kept."""

    def __init__(self, catalog: ViewCatalog, name: str, text: str, mode: str, policy: str, plans: Plans, network: Network):
        self.catalog, self.name, self.text, self.mode, self.policy, self.plans, self.network = catalog, name, text, mode, policy, plans, network
        self.waiting: list[tuple[ChangeSet, str | None]] = []

    def read(self) -> DataFrame:
        self.flush()
        return self.network.read()

    def refresh(self, changes: ChangeSet, batch: str | None = None) -> RefreshReport:
        """Refresh the catalogue, for its views share the changed tables; this view's report."""
        return self.catalog.refresh(changes, batch)[self.name]

    def flush(self) -> list[RefreshReport]:
        """Apply what waits."""
        waiting, self.waiting = self.waiting, []
        return [self.network.refresh(c, b) for c, b in waiting]

    def changes(self, generation: int) -> DataFrame | None:
        return self.network.changes(generation)


class ViewCatalog:
    """Create, read, refresh, explain and drop views.

    Views that are refreshed at once share the base tables and their changes; a deferred
    view keeps its own, as its tables lag behind.
    """

    def __init__(self, graph: PropertyGraph, folder: str | None = None):
        self.graph, self.folder, self.views = graph, folder, {}
        self.tables = base_tables(graph, "base", folder)
        self.seen: dict[str, None] = {}
        self.version = self.steps = 0
        self.garbage: list[tuple[int, Run]] = []

    def create(self, name: str, text: str, mode: str = "trail", state: str = "all", options: Options = Options(), policy: str = "immediate") -> View:
        if name in self.views:
            raise KeyError(f"view {name} exists")
        self.views[name] = self._view(name, text, mode, state, options, policy)
        self.views[name].network.load()
        self._save()
        return self.views[name]

    def _view(self, name: str, text: str, mode: str, state: str, options: Options, policy: str) -> View:
        if policy not in POLICIES:
            raise ValueError(f"no policy {policy}")
        plans = self.graph.plans(text, mode, options)
        network = Network(self.graph, plans.flat, "none" if policy == "recomputed" else state, name, self.folder, tables=self.tables)
        if policy == "deferred":
            network.owner, network.tables = True, {t: Table(x.first, Runs(f"{name}-{t}", self.folder, list(x.runs.parts))) for t, x in self.tables.items()}
        return View(self, name, text, mode, policy, plans, network)

    def refresh(self, changes: ChangeSet, batch: str | None = None) -> dict[str, RefreshReport]:
        """Refresh the views that read a changed table, at once; the others only take over the tables."""
        if batch is not None and batch in self.seen:
            return {n: RefreshReport(v.network.generation, None, 0.0, {}) for n, v in self.views.items()}
        changed = staged(self.tables, changes)
        reads = set(self.affected(ChangeSet(changed)))

        def one(item: tuple[str, View]) -> RefreshReport:
            name, view = item
            if view.policy == "deferred":
                view.waiting.append((ChangeSet(changed), batch))
                return RefreshReport(view.network.generation, None, 0.0, {})
            return view.network.apply(changed if name in reads else {}, batch)

        with ThreadPoolExecutor(max(1, min(8, len(self.views)))) as pool:
            reports = dict(zip(self.views, pool.map(one, self.views.items())))
        self.steps += 1
        self.garbage += [(self.steps, run) for table in self.tables.values() for run in table.runs.commit()]
        while self.garbage and self.garbage[0][0] <= self.steps - HISTORY:
            removed(self.graph.spark, self.garbage.pop(0)[1].path)
        self.graph = self.graph.with_tables({t: self.tables[t].now() for t in changed})
        for v in self.views.values():
            if not v.network.owner:
                v.network.graph = v.network.graph.with_tables({t: self.tables[t].now() for t in changed})
        if batch is not None:
            self.seen[batch] = None
        self._save()
        return reports

    def affected(self, changes: ChangeSet) -> list[str]:
        """Impact analysis: views with a leaf that reads a changed table."""
        return [n for n, v in self.views.items() if tables_of(v.network) & changes.tables.keys()]

    def explain(self, name: str) -> str:
        return self.views[name].plans.explain()

    def drop(self, name: str) -> None:
        del self.views[name]
        self._save()

    def execute(self, statement: str) -> DataFrame | None:
        """CREATE [DEFERRED | RECOMPUTED] VIEW name AS query, REFRESH VIEW name, DROP VIEW name, SHOW VIEWS, SELECT VIEW name."""
        words = re.match(r"(?is)^\s*(?:CREATE\s+(?:(DEFERRED|RECOMPUTED)\s+)?VIEW\s+(\w+)\s+AS\s+(.+?)|(REFRESH|DROP|SELECT)\s+VIEW\s+(\w+)|(SHOW)\s+VIEWS)\s*;?\s*$", statement)
        if not words:
            raise PlanError(f"no statement on views: {statement.strip()[:40]}")
        policy, name, text, verb, known, _ = words.groups()
        if text:
            self.create(name, text, policy=(policy or "immediate").lower())
            return None
        if verb is None:
            rows = [(n, v.policy, v.network.generation, v.text) for n, v in self.views.items()]
            return self.graph.spark.createDataFrame(rows, "name string, policy string, generation long, text string")
        if known not in self.views:
            raise KeyError(f"no view {known}")
        if verb.upper() == "SELECT":
            return self.views[known].read()
        if verb.upper() == "DROP":
            self.drop(known)
        else:
            self.views[known].flush()
            self._save()
        return None

    # -- what outlives the session
    def _save(self) -> None:
        if self.folder is None:
            return
        for v in self.views.values():
            v.flush()  # what waits is in memory only
        self.version += 1
        views = [{"name": v.name, "text": v.text, "mode": v.mode, "policy": v.policy, "state": v.network.state, **v.network.manifest(),
                  "own": {} if not v.network.owner else _paths(v.network.tables)} for v in self.views.values()]
        body = json.dumps({"views": views, "seen": list(self.seen), "tables": _paths(self.tables)})
        spark = self.graph.spark
        fs, draft = files(spark, f"{self.folder}/_draft-{self.version:09d}")
        out = fs.create(draft, True)
        out.write(bytearray(body.encode()))
        out.close()
        # a manifest is there whole or not at all
        if not fs.rename(draft, files(spark, f"{self.folder}/manifest-{self.version:09d}.json")[1]):
            raise RuntimeError(f"manifest {self.version} is there: another catalogue writes to {self.folder}")
        if self.version > 2:
            removed(spark, f"{self.folder}/manifest-{self.version - 2:09d}.json")

    @classmethod
    def open(cls, graph: PropertyGraph, folder: str) -> ViewCatalog:
        """Go on from the newest manifest in a folder; graph is over the base tables as they were at first."""
        spark = graph.spark
        fs, where = files(spark, f"{folder}/manifest-*.json")
        names = sorted(x.getPath().toString() for x in fs.globStatus(where) or ())
        if not names:
            raise FileNotFoundError(f"no manifest in {folder}")
        saved = json.loads(spark.read.text(names[-1], wholetext=True).first()["value"])
        catalog = cls(graph, folder)
        catalog.version = int(names[-1].rsplit("-", 1)[1].removesuffix(".json"))
        catalog.seen = dict.fromkeys(saved["seen"])
        _restored(spark, catalog.tables, saved["tables"])
        for v in saved["views"]:
            view = catalog.views[v["name"]] = catalog._view(v["name"], v["text"], v["mode"], v["state"], Options(), v["policy"])
            _restored(spark, view.network.tables, v["own"])
            view.network.restore(v)
        catalog.graph = graph.with_tables({t: table.now() for t, table in catalog.tables.items() if table.runs.parts})
        return catalog


def _paths(tables: dict) -> dict:
    return {t: [[p.path, p.rows] for p in table.runs.parts] for t, table in tables.items() if table.runs.parts}


def _restored(spark, tables: dict, paths: dict) -> None:
    for t, parts in paths.items():
        tables[t].runs.parts = [Run(spark.read.parquet(path), rows, path) for path, rows in parts]


def tables_of(network: Network) -> set[str]:
    """Tables behind a network's leaves."""
    graph, found = network.graph, set()
    for node in network.plan.walk():
        if isinstance(node, ScanVertices):
            found |= {t for s in graph.vertices.values() if graph.may_have(s, node.labels) for t in inputs_of(s)}
        elif isinstance(node, ScanEdges):
            found |= {t for s in graph.edge_sources(node.types) for t in inputs_of(s)}
    return found
