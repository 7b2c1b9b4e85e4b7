"""A property graph whose vertices and edges are defined over tables.

Nothing is copied: a source names a table (or derives a relation from tables), and
the expressions that give ids, endpoints, labels and properties.  Property types
come from the tables; a property that no source has is a typed null.

Tables may carry a signed weight column ``__w``; sources then pass it on, which is
how one mapping serves queries, old and new states, and change sets.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphviews.operators.nearness import near_pairs
from graphviews.plans.expr import LABELS, SOURCE, TARGET, TYPE, flat
from graphviews.plans.ops import BOTH, IN, OUT, Node, ScanEdges
from graphviews.plans.parser import parse
from graphviews.plans.rewrite import Options, Plans, compiled, pushed, seeking_ends

WEIGHT = "__w"


@dataclass(frozen=True)
class VertexSource:
    """Vertices of one kind: id and property expressions over a table.

    derive makes the relation from tables where it is no plain selection of one; tables
    names all that it reads, if it reads more than its own.  touch=((table, expression), ...)
    says that the relation falls into independent parts by the expressions' value, so that
    a change of these tables re-derives only the parts it touches.
    """

    name: str
    table: str
    id: str
    labels: tuple[str, ...]
    props: dict[str, str] = field(default_factory=dict)
    more_labels: str | None = None  # SQL array of further labels, row by row
    possible: tuple[str, ...] | None = None  # which those may be; None: any
    where: str | None = None
    derive: Callable[[dict[str, DataFrame]], DataFrame] | None = None
    touch: tuple[tuple[str, str], ...] = ()
    tables: tuple[str, ...] = ()


@dataclass(frozen=True)
class Near:
    """Edges from the smaller key to the greater between rows of the vertices' table that are near: columns key, group and place, and the width.

    The edge source's expressions read the keys as k and k2.
    """

    key: str
    group: str
    place: str
    width: float


@dataclass(frozen=True)
class EdgeSource:
    """Edges of one type between the vertices of two sources; derive, tables and touch as for vertices.

    trails(tables, low, up), where given, has the numbers of undirected trails from each source
    vertex as (what src reads, trails), or None where it cannot count these.
    """

    type: str
    table: str
    id: str
    src: str
    trg: str
    source: str
    target: str
    props: dict[str, str] = field(default_factory=dict)
    where: str | None = None
    derive: Callable[[dict[str, DataFrame]], DataFrame] | None = None
    touch: tuple[tuple[str, str], ...] = ()
    tables: tuple[str, ...] = ()
    trails: Callable[[dict[str, DataFrame], int, int | None], DataFrame | None] | None = None
    near: Near | None = None


def inputs_of(source: VertexSource | EdgeSource) -> set[str]:
    """The tables behind a source."""
    return {source.table, *source.tables}


def consolidated(df: DataFrame, positive: bool = False) -> DataFrame:
    """Equal rows merged by adding weights; rows of weight zero vanish."""
    keys = [c for c in df.columns if c != WEIGHT]
    out = df.groupBy(*[F.col(f"`{c}`") for c in keys]).agg(F.sum(WEIGHT).cast("long").alias(WEIGHT))
    return out.where(F.col(WEIGHT) > 0 if positive else F.col(WEIGHT) != 0)


class PropertyGraph:
    """Vertex and edge sources bound to tables."""

    def __init__(self, spark: SparkSession, tables: dict[str, DataFrame], vertices: list[VertexSource], edges: list[EdgeSource]):
        self.spark, self.tables = spark, tables
        self.vertices = {v.name: v for v in vertices}
        self.edges = edges
        self.scanned: set[str] | None = None
        self._once: dict[str, bool] = {}

    def of_sources(self, vertices: list[VertexSource], edges: list[EdgeSource]) -> PropertyGraph:
        """The graph with fewer sources of rows; what is known of all vertices stays known."""
        out = PropertyGraph(self.spark, self.tables, list(self.vertices.values()), edges)
        out.scanned = {v.name for v in vertices}
        return out

    def with_tables(self, tables: dict[str, DataFrame]) -> PropertyGraph:
        out = PropertyGraph(self.spark, {**self.tables, **tables}, list(self.vertices.values()), self.edges)
        out.scanned = self.scanned
        return out

    # -- what is known of labels
    def may_have(self, source: VertexSource, labels: tuple[str, ...]) -> bool:
        rest = set(labels) - set(source.labels)
        return not rest or bool(source.more_labels) and (source.possible is None or rest <= set(source.possible))

    def edge_sources(self, types: tuple[str, ...]) -> list[EdgeSource]:
        return [e for e in self.edges if not types or e.type in types]

    def ends_have_labels(self, types: tuple[str, ...], direction: str, labels: tuple[str, ...]) -> bool:
        """Whether every edge of the types is known to end in vertices with all the labels."""
        found = self.edge_sources(types)
        ends = [x for e in found for x in ((e.target,) if direction == OUT else (e.source,) if direction == IN else (e.source, e.target))]
        return bool(found) and all(set(labels) <= set(self.vertices[x].labels) for x in ends)

    def estimate(self, leaf) -> float:
        """Bytes of the tables behind a leaf, as the file system or the plan knows them, shared out by its labels."""
        edges = not hasattr(leaf, "var")
        pool = self.edge_sources(leaf.types) if edges else [s for s in self.vertices.values() if self.may_have(s, leaf.labels)]
        if edges:
            pool = [s for s in pool if leaf.direction == BOTH or self._may_end(s, leaf)]
        size = lambda t: float(str(self.tables[t]._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
        labels = () if edges else set(leaf.labels)
        return sum(size(t) / (1 if edges or labels <= set(s.labels) else 5) for s in pool for t in inputs_of(s))

    def _may_end(self, source: EdgeSource, leaf) -> bool:
        a, b = (source.source, source.target) if leaf.direction == OUT else (source.target, source.source)
        return self.may_have(self.vertices[a], leaf.v_labels) and self.may_have(self.vertices[b], leaf.w_labels)

    # -- relations
    def base(self, source) -> DataFrame:
        """The rows behind a source; weighted tables give weighted rows."""
        if source.derive is None:
            df = self.tables[source.table]
        else:
            needed = inputs_of(source)
            weighted = any(WEIGHT in self.tables[t].columns for t in needed)
            inputs = self.tables
            if weighted:  # derived relations see plain rows
                inputs = {t: _plain_rows(self.tables[t]) for t in needed}
            df = source.derive(inputs)
            if weighted:
                df = df.withColumn(WEIGHT, F.lit(1).cast("long"))
        return df.where(source.where) if source.where else df

    def property_type(self, sources, key: str) -> str:
        types = {dict(self.base(s).select(F.expr(s.props[key]).alias("x")).dtypes)["x"] for s in sources if key in s.props}
        if len(types) == 1:
            return types.pop()
        if types and types <= {"tinyint", "smallint", "int", "bigint"}:
            return "bigint"
        return "double" if types and types <= {"tinyint", "smallint", "int", "bigint", "float", "double"} else "string"

    def _select(self, source, ids: dict[str, str], wanted: list[tuple[str, str, str]], kind: dict[str, str]) -> DataFrame:
        """ids as columns, then (variable, key, expression or '') as property columns."""
        df = self.base(source)
        made = [F.expr(e).cast("long").alias(n) for n, e in ids.items()]
        made += [(F.expr(e) if e else F.lit(None)).cast(kind[flat(v, k)]).alias(flat(v, k)) for v, k, e in wanted]
        return df.select(*made, *([WEIGHT] if WEIGHT in df.columns else []))

    def _labels_expr(self, s: VertexSource) -> str:
        own = "array(" + ", ".join(f"'{x}'" for x in s.labels) + ")"
        return f"concat({own}, {s.more_labels})" if s.more_labels else own

    def scan_vertices(self, var: str, labels: tuple[str, ...] = (), props: tuple[str, ...] = (), only: str | None = None) -> DataFrame:
        """Vertices with all labels as (var, var__key...)."""
        every = [s for s in self.vertices.values() if self.may_have(s, labels)]
        kind = {flat(var, k): "array<string>" if k == LABELS else self.property_type(every, k) for k in props}
        out = []
        for s in every:
            if (only and s.name != only) or not self.may_have(s, labels) or (self.scanned is not None and s.name not in self.scanned):
                continue
            wanted = [(var, k, self._labels_expr(s) if k == LABELS else s.props.get(k, "")) for k in props]
            rest = sorted(set(labels) - set(s.labels))
            if rest:
                test = " and ".join(f"array_contains({s.more_labels}, '{x}')" for x in rest)
                s = replace(s, where=f"({s.where}) and {test}" if s.where else test)
            out.append(self._select(s, {var: s.id}, wanted, kind))
        return self._union(out, [var], kind)

    def _union(self, parts: list[DataFrame], ids: list[str], kind: dict[str, str]) -> DataFrame:
        if not parts:
            weight = f", {WEIGHT} long" if self.weighted else ""
            fields = ", ".join([*(f"`{i}` long" for i in ids), *(f"`{n}` {t}" for n, t in kind.items())])
            return self.spark.createDataFrame([], fields + weight)
        return reduce(DataFrame.unionByName, parts)

    @property
    def weighted(self) -> bool:
        return any(WEIGHT in t.columns for t in self.tables.values())

    def scan_edges(self, v: str, v_labels, e: str, types, w: str, w_labels, direction: str = OUT, props=(), ends: bool = True) -> DataFrame:
        """Edges as (v, e, w, properties); an end's vertices are joined only where a label is unsure or a property needed.

        Both directions are one pass over the edges, each given in its two orientations.
        """
        scan = ScanEdges(v, tuple(v_labels), e, tuple(types), w, tuple(w_labels), direction, tuple(props), ends)
        if (near := self.near_source(scan)) is not None and self.near_once(near):
            return self.near_edges(near, scan)
        sources = self.edge_sources(tuple(types))
        used = {x for s in sources for x in (s.source, s.target)}
        every = [s for n, s in self.vertices.items() if n in used]
        kind = {}
        for x, k in props:
            special = {LABELS: "array<string>", TYPE: "string", SOURCE: "bigint", TARGET: "bigint"}
            kind[flat(x, k)] = special.get(k) or self.property_type(sources if x == e else [s for s in every if self.may_have(s, tuple(v_labels if x == v else w_labels))], k)
        out = []
        for s in sources:
            for a, b, way in ((s.source, s.target, OUT), (s.target, s.source, IN)):
                if direction != BOTH and way != direction:
                    continue
                if direction == BOTH and s.source == s.target and way == IN:
                    continue  # the first pass gives both orientations
                va, vb = self.vertices[a], self.vertices[b]
                if not (self.may_have(va, v_labels) and self.may_have(vb, w_labels)):
                    continue
                wanted = [(e, k, {TYPE: f"'{s.type}'", SOURCE: s.src, TARGET: s.trg}.get(k) or s.props.get(k, "")) for x, k in props if x == e]
                first, second = (s.src, s.trg) if way == OUT else (s.trg, s.src)
                df = self._select(s, {v: first, e: s.id, w: second}, wanted, kind)
                if direction == BOTH and s.source == s.target:
                    rest = [F.col(f"`{c}`") for c in df.columns if c not in (v, w)]
                    turned = F.explode(F.array(F.struct(F.col(v).alias("a"), F.col(w).alias("b")), F.struct(F.col(w).alias("a"), F.col(v).alias("b"))))
                    df = df.select(*rest, turned.alias("_o")).select(F.col("_o.a").alias(v), F.col("_o.b").alias(w), *rest)
                for var, labels, vertex in ((v, v_labels, va), (w, w_labels, vb)):
                    keys = tuple(k for x, k in props if x == var)
                    unsure = not set(labels) <= set(vertex.labels)
                    if ends and (keys or unsure):
                        there = self.scan_vertices(var, tuple(labels), keys, only=vertex.name)
                        for k in keys:
                            there = there.withColumn(flat(var, k), F.col(f"`{flat(var, k)}`").cast(kind[flat(var, k)]))
                        df = weighted_join(df, there, [var])
                out.append(df)
        return self._union(out, [v, e, w], kind)

    # -- edges by nearness
    def near_source(self, scan) -> EdgeSource | None:
        """The source of an edge scan whose edges are near rows of one vertex table, which decides the ends' labels too."""
        sources = self.edge_sources(tuple(scan.types))
        if len(sources) != 1 or sources[0].near is None:
            return None
        s = sources[0]
        vertex = self.vertices[s.source]
        plain = s.source == s.target and vertex.table == s.table and not (vertex.derive or vertex.where or s.where or s.props)
        return s if plain and {*scan.v_labels, *scan.w_labels} <= set(vertex.labels) else None

    def near_once(self, source: EdgeSource) -> bool:
        """Whether each key of a near source's table stands once."""
        if source.table not in self._once:
            table = self.tables[source.table]
            rows = consolidated(table) if WEIGHT in table.columns else table.withColumn(WEIGHT, F.lit(1).cast("long"))
            found = rows.groupBy(F.expr(source.near.key).alias("k")).agg(F.sum(F.abs(WEIGHT)).alias("_n"), F.min(WEIGHT).alias("_least"))
            self._once[source.table] = not found.where("k is not null and (_n > 1 or _least < 1)").limit(1).count()
        return self._once[source.table]

    def near_rows(self, source: EdgeSource, place: dict[str, str], old: PropertyGraph | None = None) -> DataFrame:
        """Rows of a near source as (k, n, b, properties by their column in place, was, now): how often each stood in the old graph, if any, and stands."""
        near, vertex = source.near, self.vertices[source.source]
        made = [F.expr(near.key).alias("k"), F.expr(near.group).alias("n"), F.expr(near.place).alias("b")]
        made += [F.expr(self._labels_expr(vertex) if k == LABELS else vertex.props.get(k, "null")).cast("array<string>" if k == LABELS else self.property_type([vertex], k)).alias(n) for k, n in place.items()]

        def stood(graph: PropertyGraph, is_old: int) -> DataFrame:
            table = graph.tables[source.table]
            w = F.col(WEIGHT) if WEIGHT in table.columns else F.lit(1).cast("long")
            return table.select(*made, (w * is_old).alias("was"), (w * (1 - is_old)).alias("now"))

        rows = stood(self, 0) if old is None else stood(self, 0).unionByName(stood(old, 1))
        if old is None and not self.weighted:
            return rows
        return rows.groupBy(*[c for c in rows.columns if c not in ("was", "now")]).agg(F.sum("was").alias("was"), F.sum("now").alias("now")).where("was <> 0 or now <> 0")

    def near_edges(self, source: EdgeSource, scan, starts: DataFrame | None = None, old: PropertyGraph | None = None, first_props=()) -> DataFrame:
        """Edges as scan_edges has them, from runs of near rows; keys stand once.

        starts: ids of the only vertices v that matter; old: the graph before a change, then what the
        change makes of the edges; first_props: further properties of v.
        """
        near = source.near
        wanted = {scan.v: [k for x, k in scan.props if x == scan.v] + [k for k in first_props if (scan.v, k) not in scan.props], scan.w: [k for x, k in scan.props if x == scan.w]}
        place = {k: f"x{i}" for i, k in enumerate(sorted({*wanted[scan.v], *wanted[scan.w]}))}
        rows = self.near_rows(source, place, old)
        rows = rows if old is not None else rows.where("now > 0").drop("was", "now")
        if starts is not None:
            ids = starts.toDF("_start").distinct().withColumn("start", F.lit(True))
            rows = rows.join(ids, F.expr(source.src).cast("long") == F.col("_start"), "left").withColumn("start", F.coalesce("start", F.lit(False))).drop("_start")
        pairs = near_pairs(rows, near.width, scan.direction, [place[k] for k in wanted[scan.v]], [place[k] for k in wanted[scan.w]])
        low, high = F.expr(source.src).cast("long"), F.expr(source.trg).cast("long")
        special = {TYPE: F.lit(source.type), SOURCE: low, TARGET: high}
        out = {scan.v: F.when(F.col("turned"), high).otherwise(low), scan.e: F.expr(source.id).cast("long"), scan.w: F.when(F.col("turned"), low).otherwise(high)}
        out |= {flat(scan.e, k): special.get(k, F.lit(None).cast("string")) for x, k in scan.props if x == scan.e}
        out |= {flat(x, k): F.col(f"{side}{i}") for x, side in ((scan.v, "v"), (scan.w, "w")) for i, k in enumerate(wanted[x])}
        weight = [F.col(WEIGHT)] if old is not None else [F.lit(1).cast("long").alias(WEIGHT)] if self.weighted else []
        return pairs.select(*[c.alias(n) for n, c in out.items()], *weight)

    # -- nested form
    def nested_vertices(self) -> DataFrame:
        """One attribute vertex(id, labels, properties), properties as text by key."""
        parts_ = []
        for s in self.vertices.values():
            df = self.base(s)
            entries = F.map_from_entries(F.filter(F.array(*[F.struct(F.lit(k).alias("key"), F.expr(e).cast("string").alias("value")) for k, e in s.props.items()]), lambda x: x["value"].isNotNull())) if s.props else F.create_map().cast("map<string,string>")
            parts_.append(df.select(F.struct(F.expr(s.id).cast("long").alias("id"), F.expr(self._labels_expr(s)).alias("labels"), entries.alias("properties")).alias("vertex")))
        return reduce(DataFrame.unionByName, parts_)

    def nested_edges(self) -> DataFrame:
        """One attribute edge(id, src, trg, type, properties)."""
        parts_ = []
        for s in self.edges:
            df = self.base(s)
            entries = F.map_from_entries(F.filter(F.array(*[F.struct(F.lit(k).alias("key"), F.expr(e).cast("string").alias("value")) for k, e in s.props.items()]), lambda x: x["value"].isNotNull())) if s.props else F.create_map().cast("map<string,string>")
            parts_.append(df.select(F.struct(F.expr(s.id).cast("long").alias("id"), F.expr(s.src).cast("long").alias("src"), F.expr(s.trg).cast("long").alias("trg"), F.lit(s.type).alias("type"), entries.alias("properties")).alias("edge")))
        return reduce(DataFrame.unionByName, parts_)

    # -- queries
    def plans(self, query: str | Node, mode: str = "trail", options: Options = Options()) -> Plans:
        return compiled(parse(query, mode) if isinstance(query, str) else query, self, options)

    def query(self, query: str | Node, mode: str = "trail", options: Options = Options()) -> DataFrame:
        """One-time evaluation."""
        from graphviews.operators.lowering import Lowering

        return Lowering(self).df(seeking_ends(pushed(self.plans(query, mode, options).flat)))


def _plain_rows(df: DataFrame) -> DataFrame:
    """A weighted bag as plain rows."""
    if WEIGHT not in df.columns:
        return df
    rows = consolidated(df, positive=True)
    return rows.withColumn("_n", F.explode(F.sequence(F.lit(1).cast("long"), F.col(WEIGHT)))).drop("_n", WEIGHT)


def weighted_join(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    """Inner join on shared columns; weights multiply; further columns of the right that the left has are dropped."""
    right = right.drop(*[c for c in right.columns if c in left.columns and c not in on and c != WEIGHT])
    both = WEIGHT in left.columns and WEIGHT in right.columns
    if both:
        right = right.withColumnRenamed(WEIGHT, "__wr")
    out = left.join(right, on) if on else left.crossJoin(right)
    return out.withColumn(WEIGHT, F.col(WEIGHT) * F.col("__wr")).drop("__wr") if both else out


def generic_graph(vertices: DataFrame, edges: DataFrame) -> PropertyGraph:
    """A graph of two tables (id, labels, properties) and (id, src, trg, type, properties), properties a map or struct."""
    spark = vertices.sparkSession

    def keys(df: DataFrame) -> dict[str, str]:
        kind = df.schema["properties"].dataType
        if hasattr(kind, "names"):
            return {k: f"properties.`{k}`" for k in kind.names}
        found = df.select(F.explode(F.map_keys("properties")).alias("k")).distinct().collect()  # property keys, not rows
        return {r["k"]: f"properties['{r['k']}']" for r in found}

    types = sorted(r["type"] for r in edges.select("type").distinct().collect())
    vertex_source = VertexSource("vertex", "vertices", "id", (), keys(vertices), "labels")
    props = keys(edges)
    return PropertyGraph(
        spark, {"vertices": vertices, "edges": edges}, [vertex_source],
        [EdgeSource(t, "edges", "id", "src", "trg", "vertex", "vertex", props, f"type = '{t}'") for t in types],
    )
