"""Worked examples with answers by hand, and what the operators promise."""

import pytest
from pyspark.sql import functions as F

from propgraph.functions import measures
from propgraph.operators import algorithms as alg
from propgraph.operators import baselines
from propgraph.operators.graph import GraphError, PropertyGraph, difference, intersect, send_and_fold
from propgraph.operators.loops import Trace
from propgraph.plans.placement import ReplicaView, changes, grid_bound, place, routing
from propgraph.plans.scope import JoinShape, choose_access, record


def frame(spark, rows, schema):
    return spark.createDataFrame(rows, schema)


def edges(spark, pairs):
    return frame(spark, pairs, "src long, dst long")


def as_dict(df):
    return {r[0]: r[1] for r in df.collect()}


def pairs(df):
    return sorted((r["src"], r["dst"]) for r in df.collect())


def ids(df):
    return sorted(r["id"] for r in df.collect())


def test_senior_neighbours(spark):
    v = frame(spark, [(1, 50), (2, 34), (3, 34), (4, 20), (5, 61), (6, 27)], "id long, age int")
    g = PropertyGraph.build(v, edges(spark, [(1, 2), (2, 3), (4, 1), (5, 4), (5, 1), (6, 3), (3, 4)]))
    assert as_dict(alg.senior_neighbours(g, "age")) == {1: 1, 2: 1, 4: 3, 6: 1}


def test_either_end_skipping(spark):
    g = PropertyGraph.from_edges(edges(spark, [(5, 4), (6, 4), (6, 1)]))
    t = Trace()
    assert as_dict(alg.components(g, trace=t)) == {1: 1, 4: 1, 5: 1, 6: 1}
    assert len(t.rounds) == 4
    assert as_dict(alg.components(g, fresh="src"))[5] == 4
    assert as_dict(alg.components(g, via="stars")) == {1: 1, 4: 1, 5: 1, 6: 1}


def test_pagerank_two_rounds(spark):
    g = PropertyGraph.from_edges(edges(spark, [(1, 2), (1, 3), (2, 3), (3, 1)]))
    assert as_dict(alg.pagerank(g, 1)) == pytest.approx({1: 1.0, 2: 0.575, 3: 1.425})
    want = {1: 1.36125, 2: 0.575, 3: 1.06375}
    for via in ("direct", "operators", "supersteps", "gas", "classic"):
        assert as_dict(alg.pagerank(g, 2, via=via)) == pytest.approx(want), via
    assert baselines.local_pagerank([(1, 2), (1, 3), (2, 3), (3, 1)], 2) == pytest.approx(want)
    full, delta = alg.pagerank(g, 100, tol=1e-8), alg.pagerank(g, 200, tol=1e-9, mode="delta")
    assert measures.max_abs_diff(full, delta, "pr") < 1e-6


def test_isolated_vertex_keeps_the_least_rank(spark):
    g = PropertyGraph.build(frame(spark, [(1,), (2,), (9,)], "id long"), edges(spark, [(1, 2)]))
    assert as_dict(alg.pagerank(g, 3))[9] == pytest.approx(0.15)
    assert as_dict(alg.components(g))[9] == 9


HIDDEN = [(1, 2, 0), (1, 3, 0), (2, 3, 1), (3, 4, 1), (6, 3, 1), (4, 5, 2), (5, 1, 2), (4, 6, 2)]


def test_hidden_vertex(spark):
    e = frame(spark, HIDDEN, "src long, dst long, pid int")
    g = PropertyGraph.from_edges(e)
    assert as_dict(routing(e)) == {1: [0, 2], 2: [0, 1], 3: [0, 1], 4: [1, 2], 5: [2], 6: [1, 2]}
    h = g.restrict("id != 6")
    assert ids(h.vertices) == [1, 2, 3, 4, 5] and (6, 3) not in pairs(h.edges) and (4, 6) not in pairs(h.edges)
    assert as_dict(routing(h.edges)) == {1: [0, 2], 2: [0, 1], 3: [0, 1], 4: [1, 2], 5: [2]}
    assert h.vertex_rows.count() == 6 and h.rebuild_layout().vertex_rows.count() == 5
    # a message that reads no vertex must not bring hidden edges back
    assert 6 not in as_dict(alg.degrees(h))


def test_delta_shipping(spark):
    e = frame(spark, HIDDEN, "src long, dst long, pid int")
    r = routing(e)
    every = PropertyGraph.from_edges(e).vertices
    assert measures.shipped(r, every).first()[0] == 11
    assert measures.shipped(r, every.where("id = 3")).first()[0] == 2
    view = ReplicaView(r, ("x",))
    old = every.withColumn("x", F.lit(0))
    new = old.withColumn("x", F.when(F.col("id") == 3, 1).otherwise(F.col("x")))
    assert view.refresh(old).count() == 11
    assert ids(changes(old, new, ("x",))) == [3]
    assert {(x["pid"], x["x"]) for x in view.refresh(changes(old, new, ("x",))).where("id = 3").collect()} == {(0, 1), (1, 1)}


CONTRACT_V = [(1, "a", 1), (2, "a", 2), (3, "a", 4), (4, "b", 8), (5, "b", 16), (6, "a", 32)]


def test_contract(spark):
    v = frame(spark, CONTRACT_V, "id long, grp string, w long")
    g = PropertyGraph.build(v, edges(spark, [(1, 2), (3, 2), (2, 4), (3, 5), (4, 5), (5, 6)]))
    same = lambda t: t.src["grp"] == t.dst["grp"]
    c = alg.contract(g, same, {"w": F.sum})
    assert {r["id"]: r["w"] for r in c.vertices.collect()} == {1: 7, 4: 24, 6: 32}
    assert pairs(c.edges) == [(1, 4), (1, 4), (4, 6)]
    c = alg.contract(g, same, {"w": F.sum}, {"n": F.count("*")})
    assert {(r["src"], r["dst"]): r["n"] for r in c.edges.collect()} == {(1, 4): 2, (4, 6): 1}
    loop = PropertyGraph.from_edges(frame(spark, [(1, 2, 9), (2, 3, 9), (1, 3, 1)], "src long, dst long, w int"))
    heavy = lambda t: t.edge["w"] >= 5
    assert pairs(alg.contract(loop, heavy, {}).edges) == [(1, 1)]
    assert pairs(alg.contract(loop, heavy, {}, keep_loops=False).edges) == []


def test_build(spark):
    v = frame(spark, [(1, "x"), (1, "y"), (2, "z")], "id long, name string")
    e = edges(spark, [(1, 2), (2, 3)])
    g = PropertyGraph.build(v, e, merge={"name": F.min}, default={"name": F.lit("?")})
    assert as_dict(g.vertices) == {1: "x", 2: "z", 3: "?"}
    with pytest.raises(GraphError):
        PropertyGraph.build(v, e, check=True)
    with pytest.raises(GraphError):
        PropertyGraph.build(frame(spark, [(None, "x")], "id long, name string"), e, merge={}, check=True)
    with pytest.raises(GraphError):
        g.map_vertices(id=F.lit(1))


def test_repeated_ids(spark):
    g = PropertyGraph.from_edges(edges(spark, [(1, 2), (3, 2)]))
    twice = frame(spark, [(1, 5), (1, 7), (2, 9), (None, 3)], "id long, x int")
    for op in (g.attach, g.keep_matching):
        with pytest.raises(GraphError):
            op(twice)
    assert {r["id"]: r["x"] for r in g.attach(twice, merge={"x": F.max}).vertices.collect()} == {1: 7, 2: 9, 3: None}
    k = g.keep_matching(twice, merge={"x": F.max})
    assert {r["id"]: r["x"] for r in k.vertices.collect()} == {1: 7, 2: 9} and pairs(k.edges) == [(1, 2)]
    # rows that only say which ids match may repeat
    k = g.keep_matching(twice.select("id"))
    assert ids(k.vertices) == [1, 2] and as_dict(send_and_fold(k, lambda t: F.lit(1))) == {2: 1}
    with pytest.raises(GraphError):
        PropertyGraph.build(twice.where("id IS NOT NULL"), edges(spark, [(1, 2)]))


def test_restrict_and_match(spark):
    g = PropertyGraph.from_edges(edges(spark, [(1, 2), (2, 3), (3, 4)]))
    r = g.restrict("id != 2")
    assert ids(r.vertices) == [1, 3, 4] and pairs(r.edges) == [(3, 4)]
    r = g.restrict(edge_where=lambda t: t.src_id != 1)
    assert ids(r.vertices) == [1, 2, 3, 4] and pairs(r.edges) == [(2, 3), (3, 4)]
    k = g.keep_matching(frame(spark, [(1,), (3,), (4,)], "id long"))
    assert k.edges_pending and ids(k.vertices) == [1, 3, 4] and pairs(k.edges) == [(3, 4)]
    assert g.restrict("nullif(id, id) > 0").vertices.count() == 0
    assert r.layout is g.layout


def test_join_shapes(spark):
    shapes = {
        JoinShape.NONE: lambda t: F.lit(1) + t.src_id,
        JoinShape.SOURCE: lambda t: t.src["x"],
        JoinShape.TARGET: lambda t: F.when(t.dst["x"] > 0, t.edge["w"]),
        JoinShape.BOTH: lambda t: F.when(t.src["x"] > 0, t.dst["x"]),
    }
    g = PropertyGraph.build(frame(spark, [(1, 2), (2, 3)], "id long, x int"), frame(spark, [(1, 2, 5)], "src long, dst long, w int"))
    for shape, message in shapes.items():
        _, t = record(message)
        assert t.shape is shape
        plan = send_and_fold(g, message)._jdf.queryExecution().optimizedPlan().toString()
        assert plan.count("Join Inner") == shape.joins, shape
    assert choose_access(79, 100) == "index" and choose_access(80, 100) == "scan"


def test_fresh_and_access_agree(spark):
    g = PropertyGraph.build(frame(spark, [(i, i) for i in range(6)], "id long, x long"), edges(spark, [(0, 1), (1, 2), (2, 3), (4, 5)]))
    active = frame(spark, [(1,)], "id long")
    want = {"src": {2: 1}, "dst": {1: 0}, "either": {1: 0, 2: 1}, "both": {}}
    for fresh, answer in want.items():
        for access in ("index", "scan"):
            assert as_dict(send_and_fold(g, lambda t: t.src["x"], fresh=fresh, active=active, access=access)) == answer


@pytest.mark.parametrize("p", [1, 4, 7, 16, 32])
def test_grid_bound(spark, p):
    e = edges(spark, [(i, j) for i in range(12) for j in range(12) if i != j])
    most = routing(e.withColumn("pid", place("grid", p))).agg(F.max(F.size("pids"))).first()[0]
    assert most <= grid_bound(p)


def test_varint(spark):
    cases = {0: 1, 127: 1, 128: 2, 16383: 2, 16384: 3, 2**35 - 1: 5, 2**35: 6, 2**56 - 1: 8, 2**56: 9, 2**63 - 1: 9}
    df = frame(spark, [(k,) for k in cases], "x long")
    assert as_dict(df.select("x", measures.varint_bytes("x"))) == cases


def test_edge_cases(spark):
    none = PropertyGraph.from_edges(edges(spark, []))
    assert alg.pagerank(none, 2).count() == 0 and alg.components(none).count() == 0 and alg.components(none, via="stars").count() == 0
    odd = PropertyGraph.from_edges(edges(spark, [(-5, 2**57), (-5, -5), (-5, 2**57)]))
    assert as_dict(alg.components(odd)) == {-5: -5, 2**57: -5}
    assert as_dict(alg.degrees(odd, "out")) == {-5: 3}
    assert as_dict(alg.pagerank(odd, 0)) == {-5: 1.0, 2**57: 1.0}
    assert send_and_fold(odd, lambda t: F.lit(None).cast("long")).count() == 0


def test_sets_of_graphs(spark):
    g, h = (PropertyGraph.from_edges(edges(spark, e)) for e in ([(1, 2), (2, 3)], [(2, 3), (3, 4)]))
    assert pairs(intersect(g, h).edges) == [(2, 3)] and pairs(difference(g, h).edges) == [(1, 2)]


def test_edges_stay_in_a_round(spark):
    """Within a round only vertex rows and folds are exchanged: one Exchange by source, two over a vertex cut."""
    from propgraph.operators.loops import loop_scope
    from propgraph.operators.sites import FRESH, SourceSite, VertexCut, by_key, messages

    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        with loop_scope(spark):
            e = edges(spark, [(i, (i * 7 + 3) % 40) for i in range(40)])
            state = by_key(PropertyGraph.from_edges(e).vertices.select("id", F.col("id").alias("x"), F.lit(True).alias(FRESH)), "id")
            plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
            (down,), t = record(lambda t: t.src["x"])
            site = SourceSite(e)
            one = plan(state.join(messages(site.joined(t, state, "src"), down, None, F.sum), "id", "left"))
            assert one.count("Exchange") == 1, one
            (down, up), t = record(lambda t: t.src["x"], lambda t: t.dst["x"])
            cut = VertexCut(e, "grid", 4)
            view = cut.refresh(state, ["x"], ("src", "dst"))
            two = plan(state.join(messages(cut.joined(t, view, "either", "index"), down, up, F.min), "id", "left"))
            assert two.count("Exchange") == 1, two
            assert plan(cut.ship(state, ("src", "dst"))).count("Exchange") == 1
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_traces(spark):
    """Active vertices a round, as a plain simulation gave them."""
    from propgraph.sources import workloads

    d, t = "/root/testdata/sf0.01", Trace()
    alg.components(workloads.baskets(spark, d), trace=t, partitions=16)
    assert [r["active"] for r in t.rounds] == [2481, 1436, 143, 54, 8, 3]
    assert all(a["shipped"] >= b["shipped"] for a, b in zip(t.rounds, t.rounds[1:], strict=False))
    t = Trace()
    alg.pagerank(workloads.visits(spark, d), 60, tol=1e-4, trace=t)
    assert [r["changed"] for r in t.rounds] == [150, 149, 131, 21, 0]


@pytest.mark.parametrize("strategy", ["grid", "source", "target", "pair", "pair_undirected"])
def test_vertex_cut_of_any_placement(spark, strategy):
    rows = sorted({(i, (i * i + 1) % 31) for i in range(31)} | {(i, (i * 3) % 31) for i in range(0, 31, 2)})
    g = PropertyGraph.from_edges(edges(spark, rows))
    want = baselines.local_components(rows)
    for incremental in (True, False):
        for p in (1, 3, 16):
            assert as_dict(alg.components(g, strategy=strategy, partitions=p, incremental=incremental)) == want


def test_scatter_writes_edges_where_they_lie(spark):
    from propgraph.operators.loops import run_gas

    g = PropertyGraph.build(frame(spark, [(1, 1.0), (2, 2.0), (3, 4.0)], "id long, x double"), frame(spark, [(1, 2, 0.0), (2, 3, 0.0), (1, 3, 0.0)], "src long, dst long, w double"))
    out = run_gas(g, lambda t: t.src["x"] + t.edge["w"], lambda m: {"x": F.coalesce(m, F.lit(0.0))}, lambda t: {"w": t.src["x"] - t.dst["x"]}, max_rounds=2)
    x = {1: 1.0, 2: 2.0, 3: 4.0}
    w = dict.fromkeys([(1, 2), (2, 3), (1, 3)], 0.0)
    for _ in range(2):
        x = {v: sum(x[s] + w[s, d] for s, d in w if d == v) for v in x}
        w = {(s, d): x[s] - x[d] for s, d in w}
    assert as_dict(out.vertices) == x and {(r["src"], r["dst"]): r["w"] for r in out.edges.collect()} == w


def test_edge_cut_messages(spark):
    rows = [(1, 2), (3, 2), (5, 2), (2, 4), (4, 1)]
    g = PropertyGraph.from_edges(edges(spark, rows))
    for combine in (False, True):
        ranks, trace = baselines.edge_cut_pagerank(g, 3, combine, p=4)
        assert as_dict(ranks) == pytest.approx(baselines.local_pagerank(rows, 3)) and len(trace) == 3
        assert trace[0]["messages"] <= len(rows) and trace[0]["across"] <= trace[0]["messages"]
        labels, _ = baselines.edge_cut_components(g, combine, p=4)
        assert as_dict(labels) == baselines.local_components(rows)
    assert baselines.edge_cut_pagerank(g, 1, False, p=4)[1][0]["messages"] == len(rows)


def test_index_scan_reads_clusters_of_active_vertices(spark):
    from propgraph.operators.scans import ClusteredEdges

    rows = [(i, (i * 5 + 1) % 50) for i in range(50)]
    store = ClusteredEdges(edges(spark, rows), 8)
    active = frame(spark, [(3,), (11,)], "id long")
    for fresh, test in (("src", lambda a, b: a in (3, 11)), ("dst", lambda a, b: b in (3, 11)), ("either", lambda a, b: a in (3, 11) or b in (3, 11)), ("both", lambda a, b: a in (3, 11) and b in (3, 11))):
        want = sorted(r for r in rows if test(*r))
        for n in (50, 2):
            got, how, read = store.scan(active, 2, n, fresh)
            assert pairs(got) == want and how == ("index" if n == 50 else "scan")
            assert read < 50 or how == "scan" or fresh in ("either", "both")
    store.drop()


def test_several_messages_and_simplify(spark):
    g = PropertyGraph.build(frame(spark, [(1, 2), (2, 3)], "id long, x int"), frame(spark, [(1, 2, 5), (1, 2, 6), (2, 2, 1)], "src long, dst long, w int"))
    assert as_dict(send_and_fold(g, lambda t: F.array(t.src["x"], t.edge["w"]), several=True)) == {2: 2 + 5 + 2 + 6 + 3 + 1}
    assert pairs(g.simplify().edges) == [(1, 2)] and pairs(g.simplify(loops=True).edges) == [(1, 2), (2, 2)]
    assert {(r["src"], r["dst"]): r["w"] for r in g.simplify(w=F.sum("w")).edges.collect()} == {(1, 2): 11}


def test_placed_edges_lie_by_partition(spark):
    g = PropertyGraph.from_edges(edges(spark, [(i, i + 1) for i in range(30)]))
    placed = g.place_edges((F.col("src") + F.col("dst")) % 3, 3)
    got = placed.edges.withColumn("at", F.spark_partition_id()).select("pid", "at").distinct().collect()
    assert sorted((r["pid"], r["at"]) for r in got) == [(0, 0), (1, 1), (2, 2)] and placed.layout.strategy == "function"
    given = PropertyGraph.from_edges(edges(spark, [(i, i + 1) for i in range(30)]).repartition(3)).place_edges("given", 3)
    assert given.edges.select("pid").distinct().count() == 3 and given.edges.count() == 30


def test_files_and_edge_lists(spark, tmp_path):
    from propgraph.sources import files

    g = PropertyGraph.build(frame(spark, [(1, "a"), (2, "b")], "id long, name string"), edges(spark, [(1, 2), (2, 1)]))
    files.save_bucketed(g, "bucketed_graph", 2)
    h = files.load_bucketed(spark, "bucketed_graph")
    assert sorted(h.vertices.collect()) == sorted(g.vertices.collect()) and pairs(h.edges) == pairs(g.edges)
    for kind in ("vertices", "edges"):
        spark.sql(f"DROP TABLE bucketed_graph_{kind}")
    (tmp_path / "e.txt").write_text("# comment\n1 2\n  2\t3 \n\nx y\n-4 1\n")
    assert pairs(files.read_edge_list(spark, str(tmp_path / "e.txt")).edges) == [(-4, 1), (1, 2), (2, 3)]


def test_measures(spark):
    a, b = (frame(spark, r, "id long, pr double") for r in ([(1, 1.0), (2, 3.0), (3, 2.0)], [(1, 1.5), (2, 3.0), (4, 1.0)]))
    assert measures.l1_distance(a, b, "pr") == 0.5 + 2.0 + 1.0 and measures.max_abs_diff(a, b, "pr") == 0.5
    assert measures.top_k_overlap(a, b, "pr", 2) == 0.5
    e = frame(spark, HIDDEN, "src long, dst long, pid int")
    one = measures.shape_traffic(e).where("shape = 'both'").first()["shipped"]
    assert measures.job_traffic(e, 20, JoinShape.BOTH).first()["shipped"] == 20 * one
    got = measures.timed(lambda: e, trials=3)
    assert len(got["trials"]) == 3 and got["mean"] > 0 and got["sd"] >= 0
    assert measures.scaling({1: 8.0, 4: 2.0}) == {1: 1.0, 4: 4.0}
    size = measures.layout_bytes(PropertyGraph.from_edges(e).vertices, e)
    assert 0 < size["shared"] < size["own"]
    # by column the slowly rising sources compress better than by row
    sums = measures.packing(frame(spark, [(i // 30, (i * 7919) % 1000) for i in range(5000)], "src long, dst long").coalesce(1)).first()
    assert sums["n"] == 5000 and sums["columns_bytes"] < sums["rows_bytes"]


def test_routing_bitmaps(spark):
    from propgraph.plans.placement import routing_bitmaps

    e = frame(spark, HIDDEN, "src long, dst long, pid int")
    got = {r["pid"]: r["n"] for r in routing_bitmaps(e).groupBy("pid").agg(F.sum(F.bitmap_count("bitmap")).alias("n")).collect()}
    assert got == {0: 3, 1: 4, 2: 4}


def test_stream_upkeep_and_late_data(spark, tmp_path):
    from propgraph.streaming import queries as streams

    batches = [edges(spark, [(5, 4), (9, 8)]), edges(spark, [(4, 3)]), edges(spark, [(8, 3), (7, 6)])]
    assert as_dict(streams.upkeep(batches)) == {3: 3, 4: 3, 5: 3, 8: 3, 9: 3, 6: 6, 7: 6}
    for i, rows in enumerate([["10:05", "12:30"], ["12:40"], ["10:50", "12:10"], ["15:00"], ["15:01"]]):
        frame(spark, [(f"2024-01-01 {x}:00",) for x in rows], "t string").select(F.col("t").cast("timestamp").alias("at")).coalesce(1).write.parquet(str(tmp_path / f"part{i}"))
    stream = spark.readStream.schema("at timestamp").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(tmp_path))
    # 10:50 comes when 12:30 less ten minutes has long been seen: it is too late; 12:10 isn't, its window is open
    assert {str(r["begin"]): r["n"] for r in streams.late_counts(stream).collect()} == {"2024-01-01 10:00:00": 1, "2024-01-01 12:00:00": 3}


def test_baselines_agree(spark):
    rows = [(i, (i * 7 + 3) % 40) for i in range(40)] + [(i, (i * i) % 40) for i in range(40)]
    rows = sorted({(a, b) for a, b in rows if a != b})
    e = edges(spark, rows)
    g = PropertyGraph.from_edges(e)
    want = baselines.local_pagerank(rows, 4)
    assert as_dict(baselines.dataflow_pagerank(e, 4)) == pytest.approx(want)
    assert as_dict(alg.pagerank(g, 4)) == pytest.approx(want)
    assert as_dict(baselines.dataflow_components(e)) == baselines.local_components(rows) == as_dict(alg.components(g))


def test_nearest_over_all_vectors(spark, monkeypatch):
    import numpy as np

    from propgraph.operators import neighbours
    from propgraph.sources import workloads

    monkeypatch.setattr(neighbours, "GROUP", 90)
    monkeypatch.setattr(neighbours, "BLOCK", 37)
    rows = spark.read.parquet("/root/testdata/sf0.001/embeddings.parquet").collect()
    ids, x = [r["vec_id"] for r in rows], np.array([r["embedding"] for r in rows], dtype=float)
    cos = np.round(x @ x.T / np.outer(*[np.linalg.norm(x, axis=1)] * 2), 12)
    want = {(ids[i], b[1], n) for i in range(len(ids)) for n, b in enumerate(sorted((-cos[i, j], ids[j]) for j in range(len(ids)) if j != i)[:3])}
    g = workloads.nearest(spark, "/root/testdata/sf0.001")
    assert {(r["src"], r["dst"], r["rank"]) for r in g.edges.collect()} == want

    odd = [(1, [1.0, 0.0]), (2, [2.0, 0.0]), (3, [0.0, 0.0]), (4, None), (5, [1.0, None]), (6, [3.0, 0.0]), (7, [1e200, 1e200]), (8, [1.0]), (9, []), (10, [float("nan"), 1.0])]
    got = neighbours.nearest_pairs(frame(spark, odd, "id long, embedding array<double>"), 2).collect()
    assert sorted((r["src"], r["rank"], r["dst"]) for r in got) == [(1, 0, 2), (1, 1, 6), (2, 0, 1), (2, 1, 6), (6, 0, 1), (6, 1, 2), (7, 0, 1), (7, 1, 2)]
    assert neighbours.nearest_pairs(frame(spark, [], "id long, embedding array<double>"), 2).count() == 0
