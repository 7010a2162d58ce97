"""Algorithms written with the graph operators."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .graph import Layout, PropertyGraph, send_and_fold
from .loops import Trace, loop_scope, run_gas, run_supersteps, run_supersteps_classic
from .sites import by_key, kept


def degrees(g: PropertyGraph, kind: str = "total") -> DataFrame:
    """id, degree, of vertices that have such edges; reads no vertex column, so there is no join."""
    one = lambda t: F.lit(1).cast("long")
    sums = send_and_fold(g, one if kind in ("in", "total") else None, one if kind in ("out", "total") else None)
    return sums.select("id", F.col("msg").alias("degree"))


def _rank_graph(g: PropertyGraph, init: float) -> PropertyGraph:
    out = g.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("out"))
    v = g.vertices.select("id").join(out, "id", "left").select("id", F.lit(init).alias("pr"), F.coalesce("out", F.lit(0)).alias("out"))
    return PropertyGraph(v, g.edges.select("src", "dst"), g.layout)


def pagerank(g: PropertyGraph, rounds: int = 20, tol: float | None = None, reset: float = 0.15, init: float = 1.0, via: str = "direct", mode: str = "full", trace: Trace | None = None, reuse: bool = True, every: int = 1, eliminate: bool = True) -> DataFrame:
    """id, pr. Unnormalized; the rank of vertices without out-links isn't handed on.

    via: direct, operators, supersteps, gas, classic. tol stops when no rank moves by more; a trace then tells how
    many moved by more. mode 'delta' (with tol) hands on rank differences above tol only and keeps the rest for
    later. Ablations: reuse=False (direct) deals the edges out and sorts them anew every round, eliminate=False
    (operators) joins both ends though a message reads one. every: rounds between checkpoints (direct)."""
    share = lambda t: t.src["pr"] / t.src["out"]
    new = lambda m: F.lit(reset) + F.lit(1 - reset) * F.coalesce(m, F.lit(0.0))
    if mode == "delta":
        return _pagerank_delta(g, tol or 1e-4, rounds, reset, init, trace)
    spark = g.vertex_rows.sparkSession
    if via == "operators":
        r = _rank_graph(g, init)
        with loop_scope(spark):
            r = PropertyGraph(by_key(r.vertices, "id"), by_key(r.edges, "src", "dst"), r.layout)
            for _ in range(rounds):
                sums = send_and_fold(r, share, eliminate=eliminate)
                v = r.vertices.join(sums, "id", "left").select("id", new(F.col("msg")).alias("pr"), "out")
                r = PropertyGraph(kept(v), r.edge_rows, r.layout)
        return r.vertices.select("id", "pr")
    if tol is not None:
        r = _rank_graph(g, init).map_vertices(move=F.lit(None).cast("double"))
        out, t = run_supersteps(r, lambda m: {"pr": new(m), "move": F.abs(new(m) - F.col("pr"))}, share, fresh=None, max_rounds=rounds, receivers_only=False, watch=lambda v: v["move"] > tol)
        if trace is not None:
            trace.rounds += t.rounds
        return out.vertices.select("id", "pr")
    if via == "supersteps":
        out, t = run_supersteps(_rank_graph(g, init), lambda m: {"pr": new(m)}, share, fresh=None, max_rounds=rounds, receivers_only=False)
        if trace is not None:
            trace.rounds += t.rounds
        return out.vertices.select("id", "pr")
    if via == "gas":
        return run_gas(_rank_graph(g, init), share, lambda m: {"pr": new(m)}, max_rounds=rounds).vertices.select("id", "pr")
    if via == "classic":
        fold = lambda m: {"pr": new(F.aggregate(m, F.lit(0.0), lambda a, x: a + x))}
        return run_supersteps_classic(_rank_graph(g, init), fold, share, rounds).vertices.select("id", "pr")
    r = _rank_graph(g, init)
    with loop_scope(spark):
        # edges lie by source as vertices do by id, and stay there; only sums move
        e = by_key(r.edges, "src", "dst") if reuse else kept(r.edges)
        state = by_key(r.vertices, "id")
        for i in range(rounds):
            at = e if reuse else e.repartition("src").sortWithinPartitions("src")
            sent = at.join(state.select(F.col("id").alias("src"), F.try_divide("pr", "out").alias("_share")), "src")
            sums = sent.groupBy(F.col("dst").alias("id")).agg(F.sum("_share").alias("msg"))
            state = state.join(sums, "id", "left").select("id", new(F.col("msg")).alias("pr"), "out")
            if (i + 1) % every == 0 or i + 1 == rounds:
                state = kept(state)
    return state.select("id", "pr")


def _pagerank_delta(g: PropertyGraph, tol: float, rounds: int, reset: float, init: float, trace: Trace | None) -> DataFrame:
    r = _rank_graph(g, init)
    with loop_scope(g.vertex_rows.sparkSession):
        edges, start = by_key(r.edges, "src", "dst"), by_key(r.vertices, "id")

        def sums(shares: DataFrame, column: str) -> DataFrame:
            """Of the vertices in shares only; their rows and the edges lie alike, so only sums move."""
            sent = edges.join(shares.select(F.col("id").alias("src"), F.try_divide(column, "out").alias("_share")), "src")
            return sent.groupBy(F.col("dst").alias("id")).agg(F.sum("_share").alias("msg"))

        first = F.lit(reset) + F.lit(1 - reset) * F.coalesce("msg", F.lit(0.0))
        v = kept(start.join(sums(start, "pr"), "id", "left").select("id", "out", first.alias("pr"), (first - F.col("pr")).alias("left")))
        n = v.count()
        if trace is not None:
            trace.rounds.append({"round": 1, "active": n})
        for i in range(1, rounds):
            active = v.where(F.abs("left") > tol)
            count = active.count()
            if not count:
                break
            if trace is not None:
                trace.rounds.append({"round": i + 1, "active": count})
            gain = F.lit(1 - reset) * F.coalesce("msg", F.lit(0.0))
            rest = F.when(F.abs("left") > tol, F.lit(0.0)).otherwise(F.col("left"))
            v = kept(v.join(sums(active, "left"), "id", "left").select("id", "out", (F.col("pr") + gain).alias("pr"), (rest + gain).alias("left")))
    return v.select("id", "pr")


def components(g: PropertyGraph, via: str = "labels", fresh: str | None = "either", max_rounds: int = 1000, trace: Trace | None = None, incremental: bool = True, strategy: str = "grid", partitions: int | None = None) -> DataFrame:
    """id, component: the least id that each vertex reaches, edges taken both ways.

    The labels run over a vertex cut (strategy, partitions); incremental=False ships all copies every round."""
    if via == "stars":
        return _stars(g)
    start = PropertyGraph(g.vertices.select("id", F.col("id").alias("label")), g.edges.select("src", "dst"), g.layout)
    down = lambda t: F.when(t.src["label"] < t.dst["label"], t.src["label"])
    up = (lambda t: F.when(t.dst["label"] < t.src["label"], t.dst["label"])) if fresh != "out_only" else None
    out, t = run_supersteps(start, lambda m: {"label": F.least(F.col("label"), m)}, down, up, "min", "src" if fresh == "out_only" else fresh, max_rounds, incremental=incremental, strategy=strategy, partitions=partitions)
    if trace is not None:
        trace.rounds += t.rounds
    return out.vertices.select("id", F.col("label").alias("component"))


def _stars(g: PropertyGraph) -> DataFrame:
    """Pointer doubling by large and small stars: few rounds, whatever the longest chain.

    Minima are combined before the exchange and kept, so that adaptive planning can split a hub's links over tasks."""
    now = kept(g.edges.select(F.greatest("src", "dst").alias("hi"), F.least("src", "dst").alias("lo")).where("hi != lo").distinct())
    before = None
    while True:
        both = now.unionByName(now.select(F.col("lo").alias("hi"), F.col("hi").alias("lo")))
        least = kept(both.groupBy("hi").agg(F.min("lo").alias("m")).select("hi", F.least("hi", "m").alias("m")))
        large = kept(both.join(least, "hi").where("lo > hi").select(F.col("lo").alias("hi"), F.col("m").alias("lo")).where("hi != lo").distinct())
        down = kept(large.groupBy("hi").agg(F.min("lo").alias("m")))
        pairs = F.array(F.struct("hi", F.col("m").alias("lo")), F.struct(F.col("lo").alias("hi"), F.col("m").alias("lo")))
        now = kept(large.join(down, "hi").select(F.explode(pairs).alias("e")).select("e.hi", "e.lo").where("hi != lo").distinct())
        state = tuple(now.agg(F.count("*"), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first())
        if state == before:
            break
        before = state
    return g.vertices.select("id").join(now.select(F.col("hi").alias("id"), "lo"), "id", "left").select("id", F.coalesce("lo", "id").alias("component"))


def contract(g: PropertyGraph, edge_where: Callable, vertex_merge: dict[str, Callable[[Column], Column]], edge_merge: dict[str, Column] | None = None, keep_loops: bool = True, via: str = "labels") -> PropertyGraph:
    """Joins the ends of passing edges to one vertex, under the least id; the other edges are relinked. via: how components finds what is joined."""
    marked = g.map_edges(lambda t: {"_contract": F.coalesce(edge_where(t), F.lit(False))})
    marked = PropertyGraph(marked.vertices, kept(marked.edges), g.layout)
    inner = PropertyGraph(marked.vertices, marked.edge_rows.where("_contract").drop("_contract"), g.layout)
    label = components(inner, via=via)
    v = g.vertices.join(label, "id").groupBy(F.col("component").alias("id")).agg(F.count("*").alias("_members"), *[vertex_merge.get(c, F.min)(F.col(c)).alias(c) for c in g.vertex_columns]).drop("_members")
    ends = [label.select(F.col("id").alias(k), F.col("component").alias(f"_{k}")) for k in ("src", "dst")]
    e = marked.edge_rows.where("NOT _contract").join(ends[0], "src").join(ends[1], "dst").select(F.col("_src").alias("src"), F.col("_dst").alias("dst"), *g.edge_columns)
    if not keep_loops:
        e = e.where("src != dst")
    if edge_merge:
        e = e.groupBy("src", "dst").agg(*[c.alias(k) for k, c in edge_merge.items()])
    return PropertyGraph(v, e, Layout())


def senior_neighbours(g: PropertyGraph, age: str) -> DataFrame:
    """id, elders: how many older neighbours a vertex has; without any it is absent."""
    one = F.lit(1).cast("long")
    sums = send_and_fold(g, lambda t: F.when(t.src[age] > t.dst[age], one), lambda t: F.when(t.dst[age] > t.src[age], one))
    return sums.select("id", F.col("msg").alias("elders"))


def cross_edges(g: PropertyGraph, column: str) -> DataFrame:
    return g.triplets([column], [column]).where(F.col(f"src__{column}") != F.col(f"dst__{column}"))


def neighbours_agg(g: PropertyGraph, column: str, fold: str | Callable[[Column], Column], direction: str = "in") -> DataFrame:
    """id, msg: a fold of the neighbours' column, over in-links, out-links or both."""
    down, up = (lambda t: t.src[column]), (lambda t: t.dst[column])
    return send_and_fold(g, down if direction != "out" else None, up if direction != "in" else None, fold)


def label_propagation(g: PropertyGraph, rounds: int = 5) -> DataFrame:
    """id, label: each round the commonest label of the neighbours, the least at a tie; without any, its own."""
    with loop_scope(g.vertex_rows.sparkSession):
        # each edge both ways, by the vertex whose label it hands on; only counts of labels move
        e = by_key(g.edges.select(F.explode(F.array(F.struct(F.col("src").alias("f"), F.col("dst").alias("id")), F.struct(F.col("dst").alias("f"), F.col("src").alias("id")))).alias("m")).select("m.*"), "f")
        v = by_key(g.vertices.select("id", F.col("id").alias("label")), "id")
        for _ in range(rounds):
            counts = e.join(v.select(F.col("id").alias("f"), "label"), "f").groupBy("id", "label").agg(F.count("*").alias("n"))
            best = counts.groupBy("id").agg(F.min(F.struct(-F.col("n"), F.col("label").alias("label")))["label"].alias("new"))
            v = kept(v.join(best, "id", "left").select("id", F.coalesce("new", "label").alias("label")))
    return v


def compare_slices(g: PropertyGraph, first: Callable, second: Callable, rounds: int = 10) -> DataFrame:
    """id, a, b, delta: ranks on two slices of the edges."""
    from .graph import compare

    a, b = (pagerank(PropertyGraph.from_edges(g.restrict(edge_where=w).edges), rounds) for w in (first, second))
    return compare(a, b, "pr")


def top_k(df: DataFrame, k: int, by: str, *ties: str) -> DataFrame:
    return df.orderBy(F.col(by).desc(), *ties).limit(k)
