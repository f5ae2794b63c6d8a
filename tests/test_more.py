from itertools import combinations, permutations

import numpy as np
import pytest

from stepgraph.engine import Rounds
from stepgraph.model import Graph
from stepgraph.operators import centrality, neighbours, subgraph


def test_nearest_neighbours_over_blocks_equal_all_pairs(spark):
    rng = np.random.default_rng(4)
    vecs = [[float(x) for x in v] for v in np.round(rng.normal(size=(60, 6)), 1)]
    vecs[7] = vecs[3] = vecs[50]
    rows = list(enumerate(vecs)) + [(90, None), (91, [0.0] * 6), (92, [float("nan")] * 6), (93, [1.0, None, 0.0, 0.0, 0.0, 0.0]), (94, [])]
    df = spark.createDataFrame(rows, "id long, vec array<double>")
    m = np.array(vecs) / np.linalg.norm(vecs, axis=1)[:, None]
    want = {}
    for i in range(60):
        far = sorted((-round(float(m[i] @ m[j]), 9), j) for j in range(60) if j != i)[:3]
        want |= {(min(i, j), max(i, j)): 1 + c for c, j in far}
    for rows_of_block in (7, 1000):
        got = {(r.src, r.dst): r.w for r in neighbours.knn_edges(df, 3, rows_of_block).collect()}
        assert got.keys() == want.keys()
        assert all(got[k] == pytest.approx(want[k], abs=2e-9) for k in want)
    assert neighbours.knn_edges(df.limit(0)).count() == 0


@pytest.mark.parametrize("directed", [False, True])
def test_weighted_betweenness_equals_listing_all_paths(spark, directed):
    edges = [(0, 1, 1.0), (1, 2, 1.0), (0, 2, 2.0), (2, 3, 0.5), (3, 4, 1.5), (2, 4, 2.0), (4, 0, 9.0), (7, 8, 1.0)]
    ids = sorted({x for a, b, _ in edges for x in (a, b)})
    w = {(a, b): x for a, b, x in edges} | ({} if directed else {(b, a): x for a, b, x in edges})
    score = dict.fromkeys(ids, 0.0)
    for s, t in permutations(ids, 2):
        inner = [x for x in ids if x not in (s, t)]
        paths = [(s, *p, t) for n in range(4) for p in permutations(inner, n) if all(e in w for e in zip((s, *p), (*p, t), strict=True))]
        if paths:
            length = {p: sum(w[e] for e in zip(p, p[1:], strict=False)) for p in paths}
            short = [p for p in paths if length[p] == min(length.values())]
            for p in short:
                for v in p[1:-1]:
                    score[v] += (1 if directed else 0.5) / len(short)
    g = Graph.from_edges(spark.createDataFrame(edges, "src long, dst long, w double"), directed)
    assert {r.id: r.score for r in centrality.weighted_betweenness(g).collect()} == pytest.approx(score)


def test_weights_of_nothing_are_refused(spark):
    with pytest.raises(ValueError, match="above 0"):
        centrality.weighted_betweenness(Graph.from_edges(spark.createDataFrame([(1, 2, 0.0)], "src long, dst long, w double")))


def test_two_cliques_are_cut_less_than_by_the_random_split(spark):
    edges = [*combinations(range(12), 2), *combinations(range(20, 32), 2), (0, 20)]
    g = Graph.from_edges(spark.createDataFrame(edges, "src long, dst long"))
    first, last = (subgraph.label_partition(g, 2, rounds=n, seed=2) for n in (0, 6))
    assert {r.id for r in last.collect()} == {*range(12), *range(20, 32)}
    cut = [subgraph.partition_quality(g, p).first().cut_edges for p in (first, last)]
    assert cut[1] <= cut[0]


def test_keyed_arcs_do_not_move_again(spark):
    arcs = Rounds(spark).keyed(spark.range(500).selectExpr("id % 50 as src", "id as dst"), "src")
    state = spark.range(50).withColumnRenamed("id", "src").repartition(3)
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        joined = state.join(arcs, "src")
        plan = joined._jdf.queryExecution().executedPlan().toString()
        assert plan.count("Exchange hashpartitioning") == 1
        assert joined.count() == 500
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
