"""Vertex-program loops: enhanced, classic message lists, and gather-apply-scatter; and their scope."""

from __future__ import annotations

import contextlib
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.scope import Triplet, choose_access, record
from .graph import FOLDS, PropertyGraph
from .sites import FRESH, Overlay, SourceSite, VertexCut, by_key, kept, messages

#: Fixed partitioning, which the frames of a loop share; a partitioning by some of a join's keys is as good as by all.
SCOPE = {"spark.sql.adaptive.enabled": "false", "spark.sql.requireAllClusterKeysForCoPartition": "false"}


@dataclass
class Trace:
    """One entry a round: active vertices before it, receivers, changed ones, copies shipped, access, seconds."""

    rounds: list[dict] = field(default_factory=list)


@contextlib.contextmanager
def loop_scope(spark: SparkSession) -> Iterator[None]:
    """Fixed partitioning inside a loop, so that rounds join without moving what they share."""
    was = {k: spark.conf.get(k) for k in SCOPE}
    try:
        for k, v in SCOPE.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in was.items():
            spark.conf.set(k, v)


def run_supersteps(
    g: PropertyGraph,
    program: Callable[[Column], dict[str, Column]],
    to_dst: Callable | None = None,
    to_src: Callable | None = None,
    fold: str | Callable = "sum",
    fresh: str | None = "src",
    max_rounds: int = 100,
    halt: Column | None = None,
    watch: Callable[[dict[str, Column]], Column] | None = None,
    threshold: float = 0.8,
    receivers_only: bool = True,
    strategy: str | Column = "grid",
    partitions: int | None = None,
    incremental: bool = True,
    several: bool = False,
    few: float = 0.1,
) -> tuple[PropertyGraph, Trace]:
    """Rounds of send, fold and program until nothing changes, `halt` holds everywhere, or max_rounds.

    program(msg) gives new values of vertex columns; vertices that receive nothing keep theirs
    (receivers_only) or run it with a null message. A vertex is active if a written column changed, or if
    watch(new values) holds. Messages that read the source only run over edges by source, without moving a
    vertex row; others over a vertex cut (strategy, partitions), whose copies are refreshed by what has
    changed (incremental) or all anew. The trace's `shipped` counts the copies. Where only receivers run the
    program, a round with at most the share `few` of vertices active writes no whole state or view any more,
    but what has changed, which lies over them."""
    trace = Trace()
    how_fold = FOLDS[fold] if isinstance(fold, str) else fold
    (down, up), t = record(to_dst, to_src)
    cut = bool(t.dst.read) or fresh in ("dst", "either", "both")
    sides = tuple(s for s, part in (("src", t.src), ("dst", t.dst)) if part.read or fresh in (s, "either", "both"))
    reads = sorted(t.src.read | t.dst.read)
    with loop_scope(g.vertex_rows.sparkSession):
        site = VertexCut(g.edges, strategy, partitions) if cut else SourceSite(g.edges)
        start = g.vertices.withColumn(FRESH, F.lit(True))
        if cut:
            start = start.join(site.counts(sides), "id", "left").withColumn("copies", F.coalesce("copies", F.lit(0)))
        state = by_key(start, "id")
        extra = ["copies"] if cut else []
        first = state.agg(F.count("*"), F.sum("copies") if cut else F.lit(0)).first()
        n = n_active = first[0]
        ship_next = first[1] or 0
        overlay = None
        for number in range(max_rounds):
            began = time.time()
            if overlay is None and cut and number and fresh and incremental and receivers_only and watch is None and halt is None and n_active <= few * n:
                overlay = Overlay(site, state, g.vertex_columns, reads, sides)
            how, skip = choose_access(n_active, n, threshold), fresh if number else None
            if overlay:
                rows = overlay.joined(t, fresh)
            elif cut:
                view = site.refresh(state, reads, sides, incremental)
                rows = site.joined(t, view, skip, how)
            else:
                rows = site.joined(t, state, skip)
            sent = messages(rows, down, up, how_fold, several)
            joined = overlay.receive(sent) if overlay else state.drop(FRESH).join(sent, "id", "left")
            values = program(F.col("msg"))
            run = F.col("msg").isNotNull() if receivers_only else F.lit(True)
            new = {c: F.when(run, v).otherwise(F.col(c)) for c, v in values.items()}
            changed = F.lit(False)
            for c in () if watch else values:
                changed = changed | ~new[c].eqNullSafe(F.col(c))
            changed = F.coalesce(watch(new), F.lit(False)) if watch else changed
            got = F.col("msg").isNotNull()
            state = kept(joined.select("id", *[(new[c] if c in new else F.col(c)).alias(c) for c in g.vertex_columns], *extra, changed.alias(FRESH), got.alias("_got")))
            votes = F.count_if(~F.coalesce(halt, F.lit(False))) if halt is not None else F.lit(1)
            moved = F.coalesce(F.sum(F.when(F.col(FRESH) if incremental else F.lit(True), F.col("copies"))), F.lit(0)) if cut else F.lit(0)
            sums = state.agg(F.count_if(FRESH).alias("changed"), F.count_if("_got").alias("got"), votes.alias("live"), moved.alias("moved")).first()
            trace.rounds.append({"round": number + 1, "active": n_active, "receivers": sums["got"], "changed": sums["changed"], "shipped": ship_next, "access": how if skip else "scan", "seconds": time.time() - began})
            state = state.drop("_got")
            if overlay:
                overlay.rows = state
            n_active, ship_next = sums["changed"], sums["moved"]
            if not n_active or not sums["live"]:
                break
        if overlay:
            state = overlay.state()
    return PropertyGraph(state.drop(FRESH, *extra), g.edges, g.layout), trace


def run_supersteps_classic(g: PropertyGraph, program: Callable[[Column], dict[str, Column]], to_dst: Callable, max_rounds: int, combine: bool = False) -> PropertyGraph:
    """The message-list form: a vertex sees the array of its messages; nothing is combined on the way.

    With combine the messages are summed on the way, as a combiner would, and the program gets a list of one.
    A message reads its source only."""
    fold: Callable = (lambda m: F.array(F.sum(m))) if combine else F.collect_list
    (down,), t = record(to_dst)
    if t.dst.read:
        raise ValueError("a message of the classic form can't read its target")
    with loop_scope(g.vertex_rows.sparkSession):
        site = SourceSite(g.edges)
        state = by_key(g.vertices, "id")
        for _ in range(max_rounds):
            rows = state.join(messages(site.joined(t, state, None), down, None, fold), "id", "left")
            new = program(F.coalesce("msg", F.array().cast("array<double>")))
            state = kept(rows.select("id", *[new.get(c, F.col(c)).alias(c) for c in g.vertex_columns]))
    return PropertyGraph(state, g.edges, g.layout)


def run_gas(g: PropertyGraph, gather: Callable, apply: Callable[[Column], dict[str, Column]], scatter: Callable | None = None, fold: str | Callable = "sum", max_rounds: int = 20, strategy: str | Column = "grid", partitions: int | None = None) -> PropertyGraph:
    """Gather over in-edges of a vertex cut with a commutative fold, apply at the vertex, scatter to edge columns.

    Edges lie by the placement and stay there; sums are formed at each partition before they travel, so a
    vertex of many edges is worked on at many places. The scatter's new edge columns are kept where the edges lie."""
    how = FOLDS[fold] if isinstance(fold, str) else fold
    (down,), t = record(gather)
    after = Triplet()
    if scatter is not None:
        scatter(after)
    reads = sorted(t.src.read | t.dst.read | after.src.read | after.dst.read)
    with loop_scope(g.vertex_rows.sparkSession):
        site = VertexCut(g.edges, strategy, partitions)
        state = by_key(g.vertices, "id").withColumn(FRESH, F.lit(True))
        view = site.refresh(state, reads, ("src", "dst"))
        for _ in range(max_rounds):
            rows = state.join(messages(site.joined(t, view, None, "scan"), down, None, how), "id", "left")
            new = apply(F.col("msg"))
            changed = F.lit(False)
            for c, v in new.items():
                changed = changed | ~v.eqNullSafe(F.col(c))
            state = kept(rows.select("id", *[new.get(c, F.col(c)).alias(c) for c in g.vertex_columns], changed.alias(FRESH)))
            view = site.refresh(state, reads, ("src", "dst"))
            if scatter is not None:
                columns = scatter(after)
                names = list(dict.fromkeys([*site.edges.columns, *columns]))
                site.edges = kept(site.joined(after, view, None, "scan").withColumns(columns).select(*names).sortWithinPartitions("pid", "src"))
    return PropertyGraph(state.drop(FRESH), site.edges.drop("pid"), g.layout)
