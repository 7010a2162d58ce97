"""What the graph operators are compared with."""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.placement import spread
from .graph import PropertyGraph
from .loops import loop_scope
from .sites import by_key, kept


def dataflow_pagerank(edges: DataFrame, rounds: int, every: int = 5) -> DataFrame:
    """Ordinary joins and aggregates each round: no placement, nothing kept between rounds but ranks."""
    out = edges.groupBy("src").agg(F.count("*").alias("out"))
    ids = edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
    ranks = ids.withColumn("pr", F.lit(1.0))
    for i in range(rounds):
        sent = edges.join(out, "src").join(ranks.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("pr") / F.col("out")).alias("s"))
        ranks = ids.join(sent, "id", "left").select("id", (F.lit(0.15) + F.lit(0.85) * F.coalesce("s", F.lit(0.0))).alias("pr"))
        if (i + 1) % every == 0:
            ranks = kept(ranks)
    return ranks


def dataflow_components(edges: DataFrame, max_rounds: int = 1000) -> DataFrame:
    """Least labels over all edges each round, without an active set."""
    both = kept(edges.select("src", "dst").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct())
    labels = kept(both.select(F.col("src").alias("id")).distinct().withColumn("component", F.col("id")))
    for _ in range(max_rounds):
        least = both.join(labels.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id")).agg(F.min("component").alias("m"))
        new = kept(labels.join(least, "id").select("id", F.least("component", "m").alias("component"), (F.col("m") < F.col("component")).alias("moved")))
        labels = new.drop("moved")
        if not new.where("moved").limit(1).count():
            break
    return labels


def edge_cut(g: PropertyGraph, send: Callable[[], Column], fold: Callable[[Column], Column], step: Callable[[Column], Column], rounds: int, start: Column, combine: bool = False, to_end: bool = False, p: int = 16) -> tuple[DataFrame, list[dict]]:
    """Message passing over an edge cut: vertices are dealt to p partitions, edges lie with their source.

    Each round a vertex's value (column x) goes as one message along each out-edge to the target's partition,
    where the vertex gets the list of its messages. combine folds messages to one target at the sending
    partition first. A message can't read its target. Returns id, x, and per round how many messages were
    sent and how many of them crossed partitions. to_end: until no value changes; only changed ones send."""
    own = lambda c: (spread(c) % p).cast("int")
    trace: list[dict] = []
    with loop_scope(g.vertex_rows.sparkSession):
        out = g.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("out"))
        edges = by_key(g.edges.select(own("src").alias("pid"), "src", "dst", own("dst").alias("to")), "pid", "src", n=p)
        state = g.vertices.select("id").join(out, "id", "left").select(own("id").alias("pid"), "id", F.coalesce("out", F.lit(0)).alias("out"), start.alias("x"), F.lit(True).alias("live"))
        state = by_key(state, "pid", "id", n=p)
        for number in range(rounds):
            active = state.where("live") if to_end else state
            sent = edges.join(active.withColumnRenamed("id", "src"), ["pid", "src"]).select("pid", "to", "dst", send().alias("m"))
            if combine:
                sent = sent.groupBy("pid", "to", "dst").agg(fold(F.col("m")).alias("m"))
            sent = kept(sent.repartition(p, "to"))
            inbox = sent.groupBy(F.col("to").alias("pid"), F.col("dst").alias("id")).agg(F.collect_list("m").alias("inbox"))
            rows = state.join(inbox, ["pid", "id"], "left").withColumn("new", step(F.coalesce("inbox", F.array().cast(inbox.schema["inbox"].dataType))))
            state = kept(rows.select("pid", "id", "out", F.col("new").alias("x"), (~F.col("new").eqNullSafe(F.col("x"))).alias("live")))
            sums = sent.agg(F.count("*").alias("n"), F.count_if(F.col("pid") != F.col("to")).alias("across")).first()
            trace.append({"round": number + 1, "messages": sums["n"], "across": sums["across"]})
            if to_end and state.where("live").isEmpty():
                break
    return state.select("id", "x"), trace


def edge_cut_pagerank(g: PropertyGraph, rounds: int, combine: bool = False, p: int = 16) -> tuple[DataFrame, list[dict]]:
    """id, pr, and the trace of messages."""
    total = lambda inbox: F.aggregate(inbox, F.lit(0.0), lambda a, x: a + x)
    got, trace = edge_cut(g, lambda: F.col("x") / F.col("out"), F.sum, lambda inbox: F.lit(0.15) + F.lit(0.85) * total(inbox), rounds, F.lit(1.0), combine, p=p)
    return got.withColumnRenamed("x", "pr"), trace


def edge_cut_components(g: PropertyGraph, combine: bool = False, p: int = 16, max_rounds: int = 1000) -> tuple[DataFrame, list[dict]]:
    """id, component, and the trace. Labels go both ways, so every edge is also stored with its other end."""
    both = PropertyGraph(g.vertices, g.symmetrize().edges.select("src", "dst"), g.layout)
    got, trace = edge_cut(both, lambda: F.col("x"), F.min, lambda inbox: F.least(F.col("x"), F.array_min(inbox)), max_rounds, F.col("id"), combine, True, p)
    return got.withColumnRenamed("x", "component"), trace


def local_pagerank(edges: list[tuple[int, int]], rounds: int, ids: list[int] | None = None) -> dict[int, float]:
    """One process, for exact answers on small graphs."""
    ids = ids or sorted({x for e in edges for x in e})
    out: dict[int, int] = defaultdict(int)
    for s, _ in edges:
        out[s] += 1
    pr = dict.fromkeys(ids, 1.0)
    for _ in range(rounds):
        got: dict[int, float] = defaultdict(float)
        for s, d in edges:
            got[d] += pr[s] / out[s]
        pr = {i: 0.15 + 0.85 * got[i] for i in ids}
    return pr


def local_components(edges: list[tuple[int, int]], ids: list[int] | None = None) -> dict[int, int]:
    up = {i: i for i in ids or {x for e in edges for x in e}}

    def root(x: int) -> int:
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for a, b in edges:
        a, b = root(a), root(b)
        up[max(a, b)] = min(a, b)
    return {i: root(i) for i in up}
