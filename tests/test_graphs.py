"""Worked examples, invariants and agreement with the sequential counterparts."""

import math

import pytest
from pyspark.sql import functions as F

from stepgraph.baselines import sequential as seq
from stepgraph.cost import Ledger, certificate, superstep_time
from stepgraph.model import Graph
from stepgraph.operators import components, flood, rank, sets, simulation, spanning, subgraph, trees
from stepgraph.sources import generators as gen


def rows(df, *cols):
    return sorted(tuple(r) for r in df.select(*cols).collect())


def edges(spark, pairs, directed=False, n=None):
    e = spark.createDataFrame(pairs, "src long, dst long" + (", w double" if pairs and len(pairs[0]) == 3 else ""))
    return Graph.from_edges(e, directed, spark.range(n) if n else None)


def test_hooks_stop_only_when_stable(spark):
    g = edges(spark, [(0, 3), (3, 1), (1, 2), (2, 4)])
    assert rows(components.hook_shortcut(g), "id", "component") == [(i, 0) for i in range(5)]


def test_flood_on_a_path_sends_ten_messages(spark):
    led = Ledger("flood")
    assert rows(flood.min_label(gen.path(spark, 4), ledger=led), "id", "component") == [(i, 0) for i in range(4)]
    assert (led.rounds, led.messages) == (4, 10)


@pytest.mark.parametrize(("make", "want"), [(lambda s: gen.path(s, 6), 5), (lambda s: gen.cycle(s, 6), 3), (lambda s: gen.star(s, 5), 2)])
def test_diameters(spark, make, want):
    assert flood.diameter(make(spark)).first()[0] == want


def test_tour_successors(spark):
    t = {(r.src, r.dst): (r.next_src, r.next_dst) for r in trees.euler_tour(edges(spark, [(0, 1), (0, 5), (0, 6)])).collect()}
    assert t[1, 0] == (0, 5) and t[6, 0] == (0, 1) and t[0, 5] == (5, 0)


@pytest.mark.parametrize("n", [1, 2, 9])
def test_list_ranking(spark, n):
    items = spark.range(n).select("id", F.lit(2).cast("long").alias("val"), F.when(F.col("id") > 0, F.col("id") - 1).alias("pred"))
    led = Ledger("rank")
    assert rows(trees.list_rank(items, ledger=led), "id", "sum_val") == [(i, 2 * i + 2) for i in range(n)]
    assert led.messages == sum(math.ceil(math.log2(i)) for i in range(1, n + 1))


def test_orders_agree_with_depth_first_search(spark):
    g = gen.random_tree(spark, 40, 3)
    assert rows(trees.tree_orders(g), "id", "pre", "post") == rows(seq.run(g, seq.tree_orders), "id", "pre", "post")


def test_blocks_strong_components_and_forest_agree_with_baselines(spark):
    g = gen.random_graph(spark, 40, 55, 4, weights=True)
    mine, theirs = {}, {}
    for out, df in ((mine, trees.biconnected(g)), (theirs, seq.run(g, seq.blocks))):
        for r in df.collect():
            out.setdefault(r.block, set()).add((r.src, r.dst))
    assert sorted(map(sorted, mine.values())) == sorted(map(sorted, theirs.values()))
    d = Graph(g.vertices, g.edges.select("src", "dst"), True)
    assert rows(components.strong_components(d), "id", "scc") == rows(seq.run(d, seq.strong), "id", "scc")
    assert rows(spanning.minimum_spanning_forest(g), "src", "dst", "w") == rows(seq.run(g, seq.sorted_union), "src", "dst", "w")
    assert rows(sets.dominant_edge_matching(g), "src", "dst", "w") == rows(seq.run(g, seq.greedy_weight_matching), "src", "dst", "w")


def test_tied_weights_make_two_edges(spark):
    f = spanning.minimum_spanning_forest(edges(spark, [(0, 1, 2.0), (1, 2, 2.0), (0, 2, 2.0)]))
    assert (f.count(), f.agg(F.sum("w")).first()[0]) == (2, 4.0)


@pytest.mark.parametrize("seed", range(3))
def test_colours_are_proper(spark, seed):
    g = gen.path(spark, 3)
    assert sets.improper_edges(g, sets.mis_coloring(g, seed)).first()[0] == 0


def test_complete_graph_needs_all_colours(spark):
    assert sets.mis_coloring(gen.complete(spark, 5), rule="lexi").select("color").distinct().count() == 5


def test_degenerate_graphs(spark):
    lone = Graph(spark.range(2), spark.createDataFrame([], "src long, dst long"))
    assert rows(components.hook_shortcut(lone), "id", "component") == [(0, 0), (1, 1)]
    assert rows(flood.min_label(edges(spark, [(0, 0), (1, 0), (0, 1)])), "id", "component") == [(0, 0), (1, 0)]
    assert flood.reachable(gen.path(spark, 4), 0, 3) and not flood.reachable(Graph(spark.range(2), lone.edges), 0, 1)


def test_rank_mass_is_kept_when_spread(spark):
    g = edges(spark, [(0, 1), (1, 2), (0, 2)], True)
    assert rank.pagerank(g, iters=8, dangling="spread").agg(F.sum("rank")).first()[0] == pytest.approx(1)


def test_simulation_removes_along_a_path(spark):
    v = spark.createDataFrame([(0, "a"), (1, "b"), (2, "a"), (3, "b"), (4, "c")], "id long, label string")
    g = Graph(v, spark.createDataFrame([(0, 1), (2, 3), (3, 4)], "src long, dst long"), True)
    q = ({0: "a", 1: "b", 2: "c"}, [(0, 1), (1, 2)])
    want = [(0, 2), (1, 3), (2, 4)]
    assert rows(simulation.graph_simulation(*q, g), "q", "id") == want == rows(simulation.dual_simulation(*q, g), "q", "id")
    assert rows(seq.run(g, seq.counted_simulation, q_labels=q[0], q_edges=q[1]), "q", "id") == want
    assert simulation.graph_simulation({0: "z"}, [], g).count() == 0


def test_triangles_of_a_complete_graph(spark):
    assert subgraph.triangles(gen.complete(spark, 6)).count() == 20


def test_costs(spark):
    led = Ledger("x", 2, [("x", 0, 0, 3, 5, 1), ("x", 0, 1, 4, 1, 2)])
    assert superstep_time(led.table(spark), g=2.0, latency=1.0).first().time == 10.0
    tour = Ledger("tour")
    g = gen.random_tree(spark, 64, 2)
    trees.euler_tour(g, tour)
    assert tour.messages == 2 * 63 and certificate(tour, 64).balanced
    hops = Ledger("hops")
    flood.all_pairs_hops(gen.star(spark, 24), ledger=hops)
    assert not certificate(hops, 24).messages_ok


def test_chains_are_whole(spark, tmp_path):
    from stepgraph.plans import workloads

    n = 15  # more events than the first dozen of a user
    spark.range(n).selectExpr("100 - id as event_id", "1L as user_id", "timestamp_seconds(id) as ts").write.parquet(f"{tmp_path}/events.parquet")
    got = {name: rows(workloads.queries()[name](spark, str(tmp_path)), "*") for name in ("cc_flood_chain", "ecc_event_chain")}
    assert got["cc_flood_chain"] == [(i, 86) for i in range(86, 101)]
    assert got["ecc_event_chain"] == [(100 - i, max(i, n - 1 - i)) for i in reversed(range(n))]


def test_lines_of_many_documents_link_them(spark, tmp_path):
    from stepgraph.plans import workloads

    n, line = 60, "a line that every document has in common"
    spark.range(n).selectExpr("id as doc_id", f"concat('own ', id, '\\n{line}') as text").write.parquet(f"{tmp_path}/documents.parquet")
    assert workloads.queries()["doc_edges"](spark, str(tmp_path)).count() == n
    got = workloads.queries()["cc_hook_docs"](spark, str(tmp_path)).where(f"id < {n}")
    assert rows(got, "id", "component") == [(i, 0) for i in range(n)]


def test_storage_and_compute_are_measured(spark):
    hops = Ledger("hops")
    flood.all_pairs_hops(gen.star(spark, 24), ledger=hops)
    cert = certificate(hops, 24)
    n = hops.stored[-1]
    assert not cert.storage_ok and not cert.compute_ok and cert.storage_ratio == n[1] > 4 and cert.compute_ratio > 4
    tour = Ledger("tour")
    trees.euler_tour(gen.random_tree(spark, 64, 2), tour)
    cert = certificate(tour, 64)
    assert cert.storage_ok and cert.compute_ok and 1 < cert.storage_ratio < 2 and 1 < cert.compute_ratio < 2.5
