"""The property graph: a vertex table and an edge table that are views of each other's rows.

Consistency: every end of an edge has one vertex row. build() makes it so; operators that only
change properties keep it for free; restrict() and keep_matching() hide vertices by a mask, and edges
that lost an end are dropped when, and only when, somebody asks for edges (triplets drop them anyway).
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.placement import place
from ..plans.scope import JoinShape, Triplet, record
from .sites import kept, messages

VISIBLE = "_visible"


class GraphError(ValueError):
    pass


def unique(df: DataFrame, key: str) -> None:
    if not df.groupBy(key).agg(F.count("*").alias("_n")).where("_n > 1").isEmpty():
        raise GraphError(f"rows repeat for one {key}; give merge")


@dataclass(frozen=True)
class Layout:
    """How edges are placed; graphs that differ in properties only share one."""

    strategy: str = "given"
    partitions: int = 0


@dataclass(frozen=True)
class PropertyGraph:
    vertex_rows: DataFrame
    edge_rows: DataFrame
    layout: Layout
    masked: bool = False
    edges_pending: bool = False

    @classmethod
    def build(cls, vertices: DataFrame, edges: DataFrame, merge: dict[str, Callable[[Column], Column]] | None = None, default: dict[str, Column] | None = None, check: bool = True) -> PropertyGraph:
        """Folds rows of one id by `merge` (column -> aggregate), adds ends without a row with `default` values or nulls.

        Without merge, ids must be unique. That, and that no id is null, is tested by one pass over the ids, unless
        check=False says that it is known; the pass raises GraphError."""
        for df, names in ((vertices, ["id"]), (edges, ["src", "dst"])):
            if missing := [c for c in names if c not in df.columns]:
                raise GraphError(f"columns missing: {missing}")
        vertices = vertices.withColumn("id", F.col("id").cast("long"))
        edges = edges.withColumns({c: F.col(c).cast("long") for c in ("src", "dst")})
        if check:
            if not vertices.where("id IS NULL").select("id").unionByName(edges.where("src IS NULL OR dst IS NULL").select(F.col("src").alias("id"))).isEmpty():
                raise GraphError("null ids")
            if merge is None:
                unique(vertices, "id")
        props = [c for c in vertices.columns if c != "id"]
        if merge is not None:
            vertices = vertices.groupBy("id").agg(*[merge.get(c, F.min)(F.col(c)).alias(c) for c in props]) if props else vertices.distinct()
        ends = edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
        lost = ends.join(vertices.select("id"), "id", "left_anti")
        kinds = dict(vertices.dtypes)
        fill = [(default or {}).get(c, F.lit(None)).cast(kinds[c]).alias(c) for c in props]
        return cls(vertices.unionByName(lost.select("id", *fill)), edges, Layout())

    @classmethod
    def from_edges(cls, edges: DataFrame, default: dict[str, Column] | None = None) -> PropertyGraph:
        edges = edges.withColumns({c: F.col(c).cast("long") for c in ("src", "dst")})
        ends = edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
        return cls(ends.select("id", *[v.alias(k) for k, v in (default or {}).items()]), edges, Layout())

    @property
    def vertices(self) -> DataFrame:
        return self.vertex_rows.where(VISIBLE).drop(VISIBLE) if self.masked else self.vertex_rows

    @property
    def edges(self) -> DataFrame:
        if not self.edges_pending:
            return self.edge_rows
        ids = self.vertices.select("id")
        return self.edge_rows.join(ids.withColumnRenamed("id", "src"), "src", "left_semi").join(ids.withColumnRenamed("id", "dst"), "dst", "left_semi").select(*self.edge_rows.columns)

    @property
    def vertex_columns(self) -> list[str]:
        return [c for c in self.vertex_rows.columns if c not in ("id", VISIBLE)]

    @property
    def edge_columns(self) -> list[str]:
        return [c for c in self.edge_rows.columns if c not in ("src", "dst")]

    def joined(self, t: Triplet, eliminate: bool = True, edges: DataFrame | None = None) -> DataFrame:
        """Edges with the vertex columns that t has noted, joined on as few sides as these need.

        Hidden vertices: a side that isn't read is still semi-joined while edges wait for repair."""
        rows = self.edge_rows if edges is None else edges
        shape = t.shape if eliminate else JoinShape.BOTH
        for side, key in ((t.src, "src"), (t.dst, "dst")):
            if shape in (JoinShape.BOTH, JoinShape(key)):
                part = self.vertices.select(F.col("id").alias(key), *[F.col(c).alias(f"{side.prefix}{c}") for c in sorted(side.read)])
                rows = rows.join(part, key)
            elif self.edges_pending:
                rows = rows.join(self.vertices.select(F.col("id").alias(key)), key, "left_semi")
        return rows

    def triplets(self, src: list[str] | None = None, dst: list[str] | None = None) -> DataFrame:
        """src, dst, edge properties, src__x, dst__x. An unnamed side brings all of its columns."""
        t = Triplet()
        for side, names in ((t.src, src), (t.dst, dst)):
            side.read.update(self.vertex_columns if names is None else names)
        rows = self.joined(t, eliminate=False)
        ends = [f"{s.prefix}{c}" for s in (t.src, t.dst) for c in self.vertex_columns if c in s.read]
        return rows.select("src", "dst", *self.edge_columns, *ends)

    def map_vertices(self, **columns: Column) -> PropertyGraph:
        if bad := {"id", VISIBLE} & columns.keys():
            raise GraphError(f"can't be written: {bad}")
        return replace(self, vertex_rows=self.vertex_rows.withColumns(columns))

    def map_edges(self, make: Callable[[Triplet], dict[str, Column]]) -> PropertyGraph:
        t = Triplet()
        columns = make(t)
        if bad := {"src", "dst"} & columns.keys():
            raise GraphError(f"can't be written: {bad}")
        rows = self.joined(t).withColumns(columns)
        return replace(self, edge_rows=rows.select("src", "dst", *dict.fromkeys([*self.edge_columns, *columns])))

    def attach(self, table: DataFrame, on: str = "id", merge: dict[str, Callable[[Column], Column]] | None = None) -> PropertyGraph:
        """Left outer join of a table by vertex id; several rows of an id need merge."""
        more = [c for c in table.columns if c != on]
        if clash := set(more) & set(self.vertex_columns):
            raise GraphError(f"columns exist: {sorted(clash)}")
        return replace(self, vertex_rows=self.vertex_rows.join(self._one_row(table, on, more, merge), "id", "left"))

    @staticmethod
    def _one_row(table: DataFrame, on: str, columns: list[str], merge: dict[str, Callable[[Column], Column]] | None) -> DataFrame:
        """id, columns: rows of one id folded by merge; without it a repeated id raises GraphError. Null ids match nothing."""
        table = table.where(F.col(on).isNotNull()).select(F.col(on).alias("id"), *columns)
        if merge is None:
            unique(table, "id")
            return table
        folds = [merge.get(c, F.min)(F.col(c)).alias(c) for c in columns]
        return table.groupBy("id").agg(*folds) if folds else table.distinct()

    def restrict(self, vertex_where: Column | str | None = None, edge_where: Callable[[Triplet], Column] | None = None) -> PropertyGraph:
        """Keeps vertices that pass, and edges that pass and whose both ends do."""
        g = self
        if edge_where is not None:
            t = Triplet()
            test = edge_where(t)
            rows = g.joined(t).where(F.coalesce(test, F.lit(False)))
            g = replace(g, edge_rows=rows.select("src", "dst", *g.edge_columns))
        if vertex_where is not None:
            test = F.expr(vertex_where) if isinstance(vertex_where, str) else vertex_where
            test = F.coalesce(test, F.lit(False))
            rows = g.vertex_rows.withColumn(VISIBLE, (F.col(VISIBLE) & test) if g.masked else test)
            g = replace(g, vertex_rows=rows, masked=True, edges_pending=True)
        return g

    def keep_matching(self, table: DataFrame, on: str = "id", merge: dict[str, Callable[[Column], Column]] | None = None) -> PropertyGraph:
        """Inner join: vertices without a row in the table are hidden; edges are repaired when asked for.

        The table's new columns are added; several rows of an id need merge, or no new column."""
        more = [c for c in table.columns if c != on and c not in self.vertex_columns]
        other = self._one_row(table, on, more, merge if more else merge or {}).withColumn("_hit", F.lit(True))
        rows = self.vertex_rows.join(other, "id", "left")
        hit = F.coalesce("_hit", F.lit(False))
        rows = rows.withColumn(VISIBLE, (F.col(VISIBLE) & hit) if self.masked else hit).drop("_hit")
        return replace(self, vertex_rows=rows, masked=True, edges_pending=True)

    def rebuild_layout(self, partitions: int | None = None) -> PropertyGraph:
        """Hidden vertices and their edges go for good; both tables are dealt out and clustered anew."""
        n = [partitions] if partitions else []
        v = self.vertices.repartition(*n, "id").sortWithinPartitions("id")
        e = self.edges.repartition(*n, "src").sortWithinPartitions("src", "dst")
        return PropertyGraph(v, e, Layout("source", partitions or 0))

    def place_edges(self, strategy: str | Column, partitions: int) -> PropertyGraph:
        """Adds the edge column pid; one task holds each partition, clustered by source. 'given' freezes where the edges lie now."""
        if isinstance(strategy, str) and strategy == "given":
            return replace(self, edge_rows=kept(self.edges.withColumn("pid", F.spark_partition_id())), edges_pending=False, layout=Layout("given", partitions))
        pid = place(strategy, partitions) if isinstance(strategy, str) else strategy
        rows = self.edges.withColumn("pid", pid.cast("int"))
        rows = rows.repartitionById(partitions, "pid").sortWithinPartitions("pid", "src")
        return replace(self, edge_rows=rows, edges_pending=False, layout=Layout(strategy if isinstance(strategy, str) else "function", partitions))

    def adjacency(self) -> DataFrame:
        """id, neighbours: sorted targets of each source."""
        return self.edges.groupBy(F.col("src").alias("id")).agg(F.array_sort(F.collect_list("dst")).alias("neighbours"))

    def reverse(self) -> PropertyGraph:
        return replace(self, edge_rows=self.edge_rows.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *self.edge_columns), layout=Layout())

    def symmetrize(self) -> PropertyGraph:
        return replace(self, edge_rows=self.edge_rows.unionByName(self.reverse().edge_rows), layout=Layout())

    def simplify(self, loops: bool = False, **fold: Column) -> PropertyGraph:
        """Parallel edges merged, with the given aggregates as their properties."""
        rows = self.edges if loops else self.edges.where("src != dst")
        pairs = rows.groupBy("src", "dst").agg(*[c.alias(k) for k, c in fold.items()]) if fold else rows.select("src", "dst").distinct()
        return replace(self, edge_rows=pairs, edges_pending=False, layout=Layout())

    def views(self, name: str) -> None:
        """Temporary views name_vertices, name_edges and name_triplets, for SQL."""
        for kind, df in (("vertices", self.vertices), ("edges", self.edges), ("triplets", self.triplets())):
            df.createOrReplaceTempView(f"{name}_{kind}")


def union(g: PropertyGraph, h: PropertyGraph, merge: dict | None = None) -> PropertyGraph:
    return PropertyGraph.build(g.vertices.unionByName(h.vertices, True), g.edges.unionByName(h.edges, True), merge=merge or {})


def intersect(g: PropertyGraph, h: PropertyGraph) -> PropertyGraph:
    """Structure of both: common ids and pairs, with g's properties."""
    v = g.vertices.join(h.vertices.select("id"), "id", "left_semi")
    e = g.edges.join(h.edges.select("src", "dst").distinct(), ["src", "dst"], "left_semi")
    return PropertyGraph(v, e, Layout())


def difference(g: PropertyGraph, h: PropertyGraph) -> PropertyGraph:
    """g without the pairs that h has; all of g's vertices stay."""
    return PropertyGraph(g.vertices, g.edges.join(h.edges.select("src", "dst").distinct(), ["src", "dst"], "left_anti"), Layout())


def compare(a: DataFrame, b: DataFrame, column: str) -> DataFrame:
    """id, a, b, delta of one result column over two results."""
    x, y = a.select("id", F.col(column).alias("a")), b.select("id", F.col(column).alias("b"))
    return x.join(y, "id", "full").withColumn("delta", F.col("b") - F.col("a"))


FOLDS = {"sum": F.sum, "min": F.min, "max": F.max, "count": F.count, "list": F.collect_list}


def send_and_fold(
    g: PropertyGraph,
    to_dst: Callable[[Triplet], Column] | None = None,
    to_src: Callable[[Triplet], Column] | None = None,
    fold: str | Callable[[Column], Column] = "sum",
    fresh: str | None = None,
    active: DataFrame | None = None,
    access: str = "index",
    eliminate: bool = True,
    several: bool = False,
) -> DataFrame:
    """id, msg: messages of every edge to its ends, folded by receiver; nulls are no messages.

    fresh ('src', 'dst', 'either', 'both') sends only along edges whose such ends are in `active` (id).
    With access 'index' stale edges are dropped before the vertex joins, with 'scan' after them.
    several: a message is an array, each of its items a message."""
    (down, up), t = record(to_dst, to_src)
    edges = g.edge_rows
    if fresh and active is not None and access == "index":
        edges = _fresh(edges, active, fresh)
    rows = g.joined(t, eliminate, edges)
    if fresh and active is not None and access == "scan":
        rows = _fresh(rows, active, fresh)
    return messages(rows, down, up, FOLDS[fold] if isinstance(fold, str) else fold, several)


def _fresh(edges: DataFrame, active: DataFrame, fresh: str) -> DataFrame:
    if fresh in ("src", "dst"):
        return edges.join(active.select(F.col("id").alias(fresh)), fresh, "left_semi")
    if fresh == "both":
        return _fresh(_fresh(edges, active, "src"), active, "dst")
    marks = [active.select(F.col("id").alias(k), F.lit(True).alias(f"_{k}")) for k in ("src", "dst")]
    return edges.join(marks[0], "src", "left").join(marks[1], "dst", "left").where("_src OR _dst").drop("_src", "_dst")
