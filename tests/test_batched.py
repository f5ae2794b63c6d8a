"""Floods inside tasks against floods by rounds, and the costs that are told of them."""

import pytest
from pyspark.sql import functions as F

from stepgraph.baselines import sequential as seq
from stepgraph.cost import Ledger
from stepgraph.model import Graph
from stepgraph.operators import batched, centrality, flood, rank
from stepgraph.sources import generators as gen


def rows(df, *cols):
    return sorted(tuple(r) for r in df.select(*cols).collect())


@pytest.mark.parametrize("directed", [False, True])
def test_floods_in_tasks_equal_a_queue(spark, directed):
    g = gen.random_graph(spark, 90, 80, 5)
    g = Graph(g.vertices, g.edges.where("src <> dst").distinct().cache(), directed)
    near = {}
    for u, v in g.simple().arcs().select("src", "dst").collect():
        near.setdefault(u, []).append(v)
    want = []
    for s in range(90):
        dist, todo = {s: 0}, [s]
        for u in todo:
            for v in near.get(u, ()):
                if v not in dist:
                    dist[v] = dist[u] + 1
                    todo.append(v)
        want += [(s, v, d) for v, d in dist.items()]
    assert rows(flood.all_pairs_hops(g), "src", "dst", "hops") == sorted(want)
    part = g.vertices.where("id % 3 = 0")
    assert rows(flood.all_pairs_hops(g, part, max_hops=2), "src", "dst", "hops") == sorted(x for x in want if x[0] % 3 == 0 and x[2] <= 2)
    ecc = {s: max(d for x, _, d in want if x == s) for s in range(90)}
    assert rows(flood.eccentricity(g), "id", "ecc") == sorted(ecc.items())
    least, far = {s: min(v for x, v, _ in want if x == s) for s in range(90)}, {}
    for s, d in ecc.items():
        far[least[s]] = max(far.get(least[s], 0), d)
    assert rows(flood.diameter(g, by_component=True), "component", "diameter") == sorted(far.items())


def test_costs_of_a_flood_in_tasks_equal_those_of_rounds(spark, monkeypatch):
    led, want = Ledger("x"), Ledger("x")
    flood.all_pairs_hops(gen.star(spark, 5), ledger=led)
    monkeypatch.setattr(batched, "ARCS", 0)
    flood.all_pairs_hops(gen.star(spark, 5), ledger=want)
    assert sorted(led.steps) == sorted(want.steps) and [x[:2] for x in led.stored] == [x[:2] for x in want.stored] and led.combined == want.combined


def test_pairs_of_a_graph_that_fits_a_worker_are_not_capped(spark):
    assert flood.all_pairs_hops(gen.star(spark, 30), max_pairs=10).count() == 900
    assert flood.diameter(gen.star(spark, 30), max_pairs=10).first()[0] == 2


def test_baselines_from_each_vertex_are_shared_out(spark, monkeypatch):
    g = gen.random_graph(spark, 40, 50, 2)
    got = seq.run(g, seq.hops)
    assert rows(got, "src", "dst", "hops") == rows(flood.all_pairs_hops(g), "src", "dst", "hops")
    assert got.select("share").distinct().count() > 8
    n, arcs = got.count(), {r.src: r.n for r in g.simple().arcs().groupBy("src").count().withColumnRenamed("count", "n").collect()}
    assert seq.operations(g, seq.hops) == n + sum(arcs.get(r.dst, 0) for r in got.collect())
    want = {r.id: r.score for r in centrality.betweenness(g).collect()}
    assert {r.id: r.score for r in seq.run(g, seq.dependency_accumulation).collect()} == pytest.approx(want)
    monkeypatch.setattr(seq, "LIMIT", 5)
    assert seq.run(g, seq.components).count() == 40


def test_ranking_records_its_messages_once(spark, monkeypatch):
    calls, record = [], Ledger.record
    monkeypatch.setattr(Ledger, "record", lambda self, *a, **k: calls.append(a[0]) or record(self, *a, **k))
    led = Ledger("pagerank")
    rank.pagerank(gen.star(spark, 9), iters=4, ledger=led)
    assert calls == [0] and led.rounds == 4 and led.messages == 4 * 16


def test_worked_tours_read_a_given_table(spark):
    from stepgraph.plans import workloads

    tour = workloads.queries()["euler_tour_worked"](spark, "/root/testdata/sf0.001")
    assert tour.inputFiles() and tour.count() == 2 * spark.read.parquet("/root/testdata/sf0.001/orders.parquet").count()


def owed(g, sources):
    """What shortest paths from the sources owe to each vertex, by a queue."""
    near, score = {}, {r.id: 0.0 for r in g.vertices.collect()}
    for u, v in g.simple().arcs().select("src", "dst").collect():
        near.setdefault(u, []).append(v)
    for s in sources:
        dist, sigma, todo = {s: 0}, {s: 1.0}, [s]
        for u in todo:
            for v in near.get(u, ()):
                if v not in dist:
                    dist[v] = dist[u] + 1
                    todo.append(v)
                if dist[v] == dist[u] + 1:
                    sigma[v] = sigma.get(v, 0.0) + sigma[u]
        delta = dict.fromkeys(todo, 0.0)
        for u in reversed(todo):
            delta[u] = sum(sigma[u] / sigma[v] * (1 + delta[v]) for v in near.get(u, ()) if dist[v] == dist[u] + 1)
            score[u] += delta[u] if u != s else 0.0
    return score


@pytest.mark.parametrize("directed", [False, True])
@pytest.mark.parametrize("room", [1, 100])
def test_betweenness_folds_hanging_trees_and_equals_a_queue(spark, monkeypatch, directed, room):
    from stepgraph.operators import waves

    monkeypatch.setattr(waves, "ROOM", room)
    g = gen.random_graph(spark, 60, 50, 4)
    g = Graph(g.vertices, g.edges.where("src <> dst").distinct().cache(), directed)
    some = batched.fold(batched.hold(g), directed)
    assert (len(some.ids) < 60) != directed
    waved = waves.Waves(some.start, some.near, some.low, some.high)
    total = dict(zip(some.whole.tolist(), some.base.tolist(), strict=True))
    sums = some.reach * 0
    for group in waved.groups(some.sources):
        waved.dependencies(group, some.reach, some.times, sums)
    for k, x in zip(some.ids.tolist(), sums.tolist(), strict=True):
        total[k] += x
    assert total == pytest.approx(owed(g, range(60)))
    half = 1.0 if directed else 0.5
    assert {r.id: r.score for r in centrality.betweenness(g).collect()} == pytest.approx({k: x * half for k, x in owed(g, range(60)).items()})
    part = g.vertices.where("id % 3 = 0")
    assert {r.id: r.score for r in centrality.betweenness(g, part).collect()} == pytest.approx({k: x * half * 3 for k, x in owed(g, range(0, 60, 3)).items()})


def test_a_tree_needs_no_flood_for_betweenness(spark):
    g = gen.star(spark, 9)
    assert not len(batched.fold(batched.hold(g)).sources)
    assert sorted(r.score for r in centrality.betweenness(g).collect()) == [0.0] * 8 + [28.0]


@pytest.mark.parametrize("directed", [False, True])
def test_shares_of_a_baseline_are_tasks_of_their_own(spark, directed):
    g = gen.random_graph(spark, 64, 60, 7)
    g = Graph(g.vertices, g.edges.where("src <> dst").distinct().cache(), directed)
    got = seq.run(g, seq.hops).withColumn("task", F.spark_partition_id())
    assert rows(got, "src", "dst", "hops") == rows(flood.all_pairs_hops(g), "src", "dst", "hops")
    assert got.select("task").distinct().count() == seq.SHARES
    assert {r.id: r.score for r in seq.run(g, seq.dependency_accumulation).collect()} == pytest.approx({k: x / 2 for k, x in owed(g, range(64)).items()})
    arcs = {r.src: r.n for r in g.simple().arcs().groupBy("src").agg(F.count("*").alias("n")).collect()}
    ops = got.count() + sum(arcs.get(r.dst, 0) for r in got.collect())
    assert seq.operations(g, seq.hops) == seq.operations(g, seq.dependency_accumulation) == ops


def test_costs_of_ranking_are_told_of_whole_runs(spark):
    from stepgraph.plans import workloads

    g = gen.star(spark, 9)
    led = workloads.ledger_of("pagerank", g)
    assert led.rounds == 30 and led.messages == 30 * 16
    assert seq.operations(g, seq.power_iteration, iters=30) == 30 * (9 + 16)


def test_costs_of_all_hops_are_told_in_one_pass(spark, monkeypatch):
    calls, record = [], Ledger.record_all
    monkeypatch.setattr(Ledger, "record_all", lambda self, sends, steps, *a, **k: calls.append(steps) or record(self, sends, steps, *a, **k))
    led = Ledger("x")
    flood.all_pairs_hops(gen.path(spark, 5), ledger=led)
    assert calls == [[0, 1, 2, 3, 4]] and led.messages == 5 * 8 and led.rounds == 5
    assert led.stored[0][1] == 1.0 and led.stored[-1][1] == 3.0  # an end keeps five ids and has one edge
