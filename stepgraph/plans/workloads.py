"""The workloads as queries over the given tables."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines import sequential as seq
from ..cost import Ledger, certificate, superstep_time, time_processor_product, total_time
from ..engine import Rounds
from ..model import Graph
from ..operators import centrality, components, flood, local, rank, sets, simulation, spanning, subgraph, trees
from ..sources import generators
from ..sources.fixtures import SQL, duck, frame, graph, labelled
from . import oracles, relational, reports

Query = Callable[[SparkSession, str], DataFrame]
ALL: dict[str, tuple[Query, str | None]] = {}

CHAIN = ({0: "BUILDING", 1: "1-URGENT", 2: "PROMO"}, [(0, 1), (1, 2)])
TALK = ({0: "user", 1: "assistant", 2: "user"}, [(0, 1), (1, 2)])


def add(name: str, query: Query, sql: str | None = None) -> None:
    ALL[name] = (query, sql)


def one(spark: SparkSession, **cells) -> DataFrame:
    return spark.createDataFrame([tuple(cells.values())], ", ".join(f"{k} {'boolean' if isinstance(v, bool) else 'double' if isinstance(v, float) else 'long'}" for k, v in cells.items()))


def _first_id(g: Graph) -> DataFrame:
    return g.vertices.agg(F.min("id").alias("id"))


# Hop distances ------------------------------------------------------------------------------------------------------
add("diameter_user_hop", lambda s, d: flood.diameter(graph(s, d, "user_hop")), oracles.hops("user_hop") + "select max(hops) as diameter from r")
add("ecc_event_chain", lambda s, d: local.eccentricity(graph(s, d, "event_chain")), "select event_id as id, greatest(nth - 1, n - nth)::int as ecc from (select event_id, row_number() over (partition by user_id order by ts, event_id) as nth, count(*) over (partition by user_id) as n from events) as q where n > 1")
add("ecc_batches_user_hop", lambda s, d: flood.eccentricity(graph(s, d, "user_hop"), batches=2), oracles.hops("user_hop") + "select src as id, max(hops) as ecc from r group by src")
add("ecc_directed_hop_sparse", lambda s, d: flood.eccentricity(graph(s, d, "hop_sparse", True)), oracles.hops("hop_sparse", True) + "select src as id, max(hops) as ecc from r group by src")
add("diameter_by_component_supply_thin", lambda s, d: flood.diameter(graph(s, d, "supply_thin"), by_component=True), oracles.hops("supply_thin") + ", x as (select src, min(dst) as component, max(hops) as ecc from r group by src) select component, max(ecc) as diameter from x group by component")
add("apsp_user_hop", lambda s, d: flood.all_pairs_hops(graph(s, d, "user_hop")), oracles.hops("user_hop") + "select src, dst, hops from r")
add("sketch_user_hop", lambda s, d: flood.neighbourhood_sketch(graph(s, d, "user_hop"), 3))
# Link ranking -------------------------------------------------------------------------------------------------------
rounded = lambda df: df.select("id", F.round("rank", 10).alias("rank"))
add("pagerank_page_leak", lambda s, d: rounded(rank.pagerank(graph(s, d, "page_link", True), iters=10)), oracles.pagerank("page_link", 10, True))
add("pagerank_page_spread", lambda s, d: rounded(rank.pagerank(graph(s, d, "page_link", True), iters=10, dangling="spread")), oracles.pagerank("page_link", 10, True, True))
for name in ("supply", "supply_thin"):
    add(f"pagerank_{name}", lambda s, d, name=name: rounded(rank.pagerank(graph(s, d, name), iters=10)), oracles.pagerank(name, 10, False))


def pagerank_tol(s: SparkSession, d: str) -> DataFrame:
    led = Ledger("pagerank")
    g = graph(s, d, "page_link", True)
    got = rank.pagerank(g, iters=60, tol=1e-6, dangling="spread", ledger=led).agg((F.abs(F.sum("rank") - 1) < 1e-9).alias("whole"))
    return got.withColumn("settled", F.lit(led.rounds < 60))


add("pagerank_tol", pagerank_tol, "select true as whole, true as settled")
# Components ---------------------------------------------------------------------------------------------------------
add("cc_flood_chain", lambda s, d: flood.min_label(graph(s, d, "event_chain")), oracles.chain_components())
add("cc_flood_supply_thin", lambda s, d: flood.min_label(graph(s, d, "supply_thin")), oracles.components("supply_thin"))
add("cc_flood_supply_forest", lambda s, d: flood.min_label(graph(s, d, "supply_forest")), oracles.components("supply_forest"))
add("cc_hook_chain", lambda s, d: components.hook_shortcut(graph(s, d, "event_chain")), oracles.chain_components())
add("cc_hook_basket", lambda s, d: components.hook_shortcut(graph(s, d, "basket_thin")), oracles.components("basket_thin"))
add("cc_hook_docs", lambda s, d: components.hook_shortcut(graph(s, d, "doc_overlap"), star_hook=False), oracles.components("doc_overlap"))


def engines_agree(s: SparkSession, d: str) -> DataFrame:
    g = graph(s, d, "supply_thin")
    a, b = flood.min_label(g), components.hook_shortcut(g).withColumnRenamed("component", "other")
    return a.join(b, "id", "full").agg(F.count_if(~F.col("component").eqNullSafe(F.col("other"))).alias("mismatches"))


add("cc_engines_agree", engines_agree, "select 0::bigint as mismatches")
add("wcc_hop_sparse", lambda s, d: components.weak_components(graph(s, d, "hop_sparse", True)), oracles.components("hop_sparse"))
add("wcc_page", lambda s, d: components.weak_components(graph(s, d, "page_link", True), engine="flood"), oracles.components("page_link"))
add("scc_hop_sparse", lambda s, d: components.strong_components(graph(s, d, "hop_sparse", True)), oracles.scc("hop_sparse"))
add("bcc_supply_thin", lambda s, d: trees.biconnected(graph(s, d, "supply_thin")).groupBy("block").agg(F.count("*").alias("n")).groupBy("n").agg(F.count("*").alias("blocks")))
add("bridges_supply_thin", lambda s, d: trees.bridges(trees.biconnected(graph(s, d, "supply_thin"))), oracles.bridge_edges("supply_thin"))
add("cut_vertices_supply_thin", lambda s, d: trees.articulation_points(trees.biconnected(graph(s, d, "supply_thin"))), oracles.cut_vertices("supply_thin"))
# Trees --------------------------------------------------------------------------------------------------------------
add("euler_tour_geo", lambda s, d: trees.euler_tour(graph(s, d, "geo_tree")), oracles.TOUR.format(t=duck("geo_tree")))
# The worked example is a star; these are the stars of the customers and their orders.
add("euler_tour_worked", lambda s, d: trees.euler_tour(graph(s, d, "order_stars")), oracles.TOUR.format(t=duck("order_stars")))
add("tree_orders_geo", lambda s, d: trees.tree_orders(graph(s, d, "geo_tree")).drop("root"), oracles.tree_orders("geo_tree"))
EVENT_LIST = "select event_id as id, cast(round(value * 100) as bigint) as val, lag(event_id) over (partition by user_id order by ts, event_id) as pred from {events}"


def event_list(s: SparkSession, d: str) -> DataFrame:
    return s.sql(EVENT_LIST, events=s.read.parquet(f"{d}/events.parquet"))


add("list_rank_events", lambda s, d: trees.list_rank(event_list(s, d)).select("id", "sum_val"), oracles.RANK)


def list_rank_rounds(s: SparkSession, d: str) -> DataFrame:
    led = Ledger("rank")
    trees.list_rank(event_list(s, d), ledger=led)
    return one(s, rounds=sum(1 for x in led.active if x), messages=led.messages)


add("list_rank_rounds", list_rank_rounds, "with x as (select row_number() over (partition by user_id order by ts, event_id) as i from events) select ceil(log2(max(i)))::bigint as rounds, sum(ceil(log2(i)))::bigint as messages from x")
# Spanning forests ---------------------------------------------------------------------------------------------------


def forest_check(method: str, name: str) -> Query:
    def query(s: SparkSession, d: str) -> DataFrame:
        g = graph(s, d, name)
        f = components.spanning_forest(g, method)
        same = components.hook_shortcut(Graph(g.vertices, f)).join(components.hook_shortcut(g).withColumnRenamed("component", "c"), "id").agg(F.count_if(F.col("component") != F.col("c")).alias("split"))
        n = f.join(g.simple().edges.select("src", "dst"), ["src", "dst"], "left_semi").agg(F.count("*").alias("edges"))
        return n.crossJoin(same)

    return query


for key, m, name in (("hook", "hook", "supply_thin"), ("bfs", "bfs", "supply_thin"), ("basket", "hook", "basket_thin")):
    add(f"spanning_forest_{key}", forest_check(m, name), f"with x as ({oracles.components(name)}) select (count(*) - count(distinct component))::bigint as edges, 0::bigint as split from x")
add("msf_supply_thin", lambda s, d: spanning.minimum_spanning_forest(graph(s, d, "supply_thin")), oracles.fold_forest("supply_thin"))
add("msf_supply_forest", lambda s, d: spanning.minimum_spanning_forest(graph(s, d, "supply_forest")), oracles.fold_forest("supply_forest"))
add("msf_trade", lambda s, d: spanning.minimum_spanning_forest(graph(s, d, "trade")), oracles.fold_forest("trade"))
add("msf_trade_by_dest", lambda s, d: spanning.minimum_spanning_forest(graph(s, d, "trade"), tie="dest").agg(F.sum("w").alias("total")), f"select sum(w) as total from ({oracles.fold_forest('trade')}) as f")
add("spanning_forest_bfs_edges", lambda s, d: components.spanning_forest(graph(s, d, "supply_thin"), "bfs"), oracles.breadth_tree("supply_thin"))
add("msf_embed", lambda s, d: spanning.minimum_spanning_forest(graph(s, d, "embed_knn")), oracles.fold_forest("embed_knn"))
# Independent sets and matching --------------------------------------------------------------------------------------
add("color_lexi_trade", lambda s, d: sets.mis_coloring(graph(s, d, "trade"), rule="lexi"), oracles.fold_colours("trade"))
add("color_lexi_supply_thin", lambda s, d: sets.mis_coloring(graph(s, d, "supply_thin"), rule="lexi"), oracles.fold_colours("supply_thin"))


add("color_lexi_embed", lambda s, d: sets.mis_coloring(graph(s, d, "embed_knn"), rule="lexi"), oracles.fold_colours("embed_knn"))


def random_colours(s: SparkSession, d: str, name: str) -> DataFrame:
    g = graph(s, d, name)
    c = sets.mis_coloring(g, seed=3)
    return sets.improper_edges(g, c).select(F.col("n").cast("long").alias("improper"))


for name in ("supply_forest", "embed_knn"):
    add(f"color_random_{name.removesuffix('_knn')}", lambda s, d, name=name: random_colours(s, d, name), "select 0::bigint as improper")


def random_mis(s: SparkSession, d: str, name: str) -> DataFrame:
    g = graph(s, d, name)
    m = sets.maximal_independent_set(g, seed=5)
    arcs = g.symmetrized().arcs().join(m.withColumnRenamed("id", "src"), "src").where("in_mis").select(F.col("dst").alias("id")).distinct().withColumn("near", F.lit(True))
    x = m.join(arcs, "id", "left").fillna(False, ["near"])
    return x.agg(F.count_if(F.col("in_mis") & F.col("near")).alias("adjacent"), F.count_if(~F.col("in_mis") & ~F.col("near")).alias("uncovered"))


for name in ("supply_thin", "embed_knn"):
    add(f"mis_random_{name.removesuffix('_knn')}", lambda s, d, name=name: random_mis(s, d, name), "select 0::bigint as adjacent, 0::bigint as uncovered")
add("match_weighted_supply_thin", lambda s, d: sets.dominant_edge_matching(graph(s, d, "supply_thin")), oracles.fold_matching("supply_thin"))
add("match_bipartite_supply_thin", lambda s, d: sets.bipartite_matching(graph(s, d, "supply_thin"), rule="lexi"), oracles.lexi_bipartite("supply_thin", 30))


def random_matching(s: SparkSession, d: str) -> DataFrame:
    g = graph(s, d, "page_host")
    m = sets.bipartite_matching(g, seed=2)
    free = g.edges.join(m.select(F.col("left").alias("src")), "src", "left_anti").join(m.select(F.col("right").alias("dst")), "dst", "left_anti").agg(F.count("*").alias("augmentable"))
    twice = m.agg((F.count("*") * 2 - F.count_distinct("left") - F.count_distinct("right")).alias("conflicts"))
    return twice.crossJoin(free)


add("match_bipartite_page_host", random_matching, "select 0::bigint as conflicts, 0::bigint as augmentable")
# Centrality and paths -----------------------------------------------------------------------------------------------
add("betweenness_user_hop", lambda s, d: centrality.betweenness(graph(s, d, "user_hop")).select("id", F.round("score", 6).alias("score")), oracles.betweenness("user_hop"))
add("betweenness_sampled_supply_thin", lambda s, d: centrality.betweenness(graph(s, d, "supply_thin"), graph(s, d, "supply_thin").vertices.where("id % 50 = 0")))
add("betweenness_supply_thin", lambda s, d: centrality.betweenness(graph(s, d, "supply_thin")).select("id", F.round("score", 6).alias("score")), oracles.betweenness("supply_thin"))
add("betweenness_weighted_trade", lambda s, d: centrality.weighted_betweenness(graph(s, d, "trade")).select("id", F.round("score", 6).alias("score")), oracles.weighted_betweenness("trade"))
add("sssp_embed", lambda s, d: flood.shortest_paths(graph(s, d, "embed_knn"), _first_id(graph(s, d, "embed_knn"))).select("id", F.round("dist", 6).alias("dist")), oracles.sssp("embed_knn"))
add("sssp_supply_thin", lambda s, d: flood.shortest_paths(graph(s, d, "supply_thin"), _first_id(graph(s, d, "supply_thin"))).select("id", F.round("dist", 6).alias("dist")), oracles.sssp("supply_thin"))
add("bfs_supply", lambda s, d: flood.shortest_paths(graph(s, d, "supply"), _first_id(graph(s, d, "supply")), weighted=False).select("id", F.col("dist").cast("int").alias("hops")), oracles.hops("supply", sources="where id = (select min(id) from v)") + "select dst as id, hops from r")
add("sssp_geo", lambda s, d: flood.shortest_paths(graph(s, d, "geo_tree"), s.range(1), weighted=False).select("id", F.col("dist").cast("long").alias("depth")), f"select id, depth from ({oracles.tree_orders('geo_tree')}) as t")
# Simulation ---------------------------------------------------------------------------------------------------------
turns = lambda s, d: labelled(s, d, "turns", "turn_labels")
entity = lambda s, d: labelled(s, d, "entity_chain", "entity_labels")
for name, g, q, e, v in (("turns", turns, TALK, "turns", "turn_labels"), ("entity_chain", entity, CHAIN, "entity_chain", "entity_labels")):
    add(f"sim_{name}", lambda s, d, g=g, q=q: simulation.graph_simulation(*q, g(s, d)), oracles.simulation(e, v, *q))
    add(f"dual_{name}", lambda s, d, g=g, q=q: simulation.dual_simulation(*q, g(s, d)), oracles.simulation(e, v, *q, rounds=4, dual=True))
    add(f"strong_{name}", lambda s, d, g=g, q=q: simulation.strong_simulation(*q, g(s, d)), oracles.strong_chain(e, v, *q, rounds=4))
# Baselines ----------------------------------------------------------------------------------------------------------
for name, method, g, out, sql in (
    ("hops", seq.hops, "user_hop", None, oracles.hops("user_hop") + "select src, dst, hops::bigint as hops from r"),
    ("components", seq.components, "basket_thin", None, oracles.components("basket_thin")),
    ("power_iteration", seq.power_iteration, "supply_thin", {"rank": 10}, oracles.pagerank("supply_thin", 10, False)),
    ("blocks_bridges", seq.blocks, "supply_thin", "bridges", oracles.bridge_edges("supply_thin")),
    ("tree_orders", seq.tree_orders, "geo_tree", None, f"select id, pre, post from ({oracles.tree_orders('geo_tree')}) as t"),
    ("sorted_union", seq.sorted_union, "supply_thin", None, oracles.fold_forest("supply_thin")),
    ("heap_forest", seq.heap_forest, "supply_thin", None, oracles.fold_forest("supply_thin")),
    ("colours", seq.lexicographic_colours, "supply_thin", None, oracles.fold_colours("supply_thin")),
    ("weight_matching", seq.greedy_weight_matching, "supply_thin", None, oracles.fold_matching("supply_thin")),
    ("dependency", seq.dependency_accumulation, "user_hop", {"score": 6}, oracles.betweenness("user_hop")),
    ("heap_paths", seq.heap_paths, "supply_thin", {"dist": 6}, oracles.sssp("supply_thin")),
):

    def baseline(s, d, method=method, g=g, out=out):
        got = seq.run(graph(s, d, g), method).drop("ops", "share")
        if out == "bridges":
            return trees.bridges(got)
        return got.withColumns({k: F.round(k, v) for k, v in (out or {}).items()})

    add(f"baseline_{name}", baseline, sql)
add("baseline_strong", lambda s, d: seq.run(graph(s, d, "hop_sparse", True), seq.strong).drop("ops"), oracles.scc("hop_sparse"))
add("baseline_tour", lambda s, d: seq.run(graph(s, d, "geo_tree"), seq.tree_tour).drop("ops"), oracles.TOUR.format(t=duck("geo_tree")))
add("baseline_breadth_tree", lambda s, d: seq.run(graph(s, d, "supply_thin"), seq.breadth_tree).drop("ops"), oracles.breadth_tree("supply_thin"))
add("baseline_strong_balls", lambda s, d: seq.run(turns(s, d), seq.strong_balls, q_labels=TALK[0], q_edges=TALK[1], radius=simulation.query_diameter(*TALK)).drop("ops"), oracles.strong_chain("turns", "turn_labels", *TALK, rounds=4))
add("baseline_bipartite", lambda s, d: seq.run(graph(s, d, "page_host", True), seq.greedy_bipartite).agg(F.count("*").alias("pairs")), f"select count(distinct dst) as pairs from ({duck('page_host')}) as g")
for dual in (False, True):
    add(f"baseline_{'dual' if dual else 'simulation'}", lambda s, d, dual=dual: seq.run(turns(s, d), seq.counted_simulation, q_labels=TALK[0], q_edges=TALK[1], dual=dual).drop("ops"), oracles.simulation("turns", "turn_labels", *TALK, rounds=4, dual=dual))
# Costs --------------------------------------------------------------------------------------------------------------


#: Rounds of link ranking that costs are told of, as many as ``rank.pagerank`` makes unless told otherwise.
RANK_ROUNDS = 30


def ledger_of(algo: str, g: Graph, p: int = 8, iters: int = RANK_ROUNDS) -> Ledger:
    led = Ledger(algo, p)
    {"pagerank": lambda: rank.pagerank(g, iters=iters, ledger=led), "flood": lambda: flood.min_label(g, ledger=led), "hook": lambda: components.hook_shortcut(g, ledger=led), "tour": lambda: trees.euler_tour(g, ledger=led), "diameter": lambda: flood.all_pairs_hops(g, ledger=led)}[algo]()
    return led


add("bsp_pagerank_ledger", lambda s, d: ledger_of("pagerank", graph(s, d, "supply"), iters=3).table(s).select("step", "proc", "sent"), f"with {oracles.sym('supply')}, x as (select (src % 8)::int as proc, count(*) as sent from e group by 1) select k::int as step, proc, sent from x cross join range(0, 3) as t(k)")
add("bsp_tour_ledger", lambda s, d: ledger_of("tour", graph(s, d, "geo_tree")).table(s).where("sent > 0").select("proc", "sent", "received"), f"with {oracles.sym('geo_tree')}, a as (select (src % 8)::int as proc, count(*) as sent from e group by 1), b as (select (dst % 8)::int as proc, count(*) as received from e group by 1) select proc, sent, received from a join b using (proc)")
add("superstep_times", lambda s, d: superstep_time(ledger_of("flood", graph(s, d, "supply_forest")).table(s), g=2.0, latency=50.0))
add("time_processor_product", lambda s, d: time_processor_product(ledger_of("hook", graph(s, d, "supply_forest")).table(s)))
# A tour has two rounds: all arcs are sent, and then every vertex looks at what it got.
add("total_time", lambda s, d: total_time(ledger_of("tour", graph(s, d, "geo_tree")).table(s)), f"with {oracles.sym('geo_tree')}, a as (select src % 8 as proc, count(*) as sent, count(distinct src) as acting from e group by 1), b as (select dst % 8 as proc, count(*) as received from e group by 1) select 'tour' as algo, (max(acting + sent + received) + max(acting))::double as time, 2::bigint as rounds from a join b using (proc)")


def balance(algo: str, make: Callable, c: float = 4.0) -> Query:
    def query(s: SparkSession, d: str) -> DataFrame:
        g, led = make(s, d), Ledger(algo)
        led = ledger_of(algo, g)
        cert = certificate(led, g.vertices.count(), c)
        return one(s, messages_ok=cert.messages_ok, rounds_ok=cert.rounds_ok)

    return query


add("balance_tour", balance("tour", lambda s, d: graph(s, d, "geo_tree")), "select true as messages_ok, true as rounds_ok")
add("balance_flood", balance("flood", lambda s, d: generators.path(s, 48), c=2.0), "select true as messages_ok, false as rounds_ok")
add("balance_diameter", balance("diameter", lambda s, d: generators.star(s, 32), c=4.0), "select false as messages_ok, true as rounds_ok")
add("balance_hook_star", balance("hook", lambda s, d: generators.path(s, 64), c=4.0))


def balance_verdicts(s: SparkSession, d: str) -> DataFrame:
    """All four parts of the balance test, with the worst ratio to degree + 1 of each of the first three and its vertex."""
    rows = []
    for algo, g, c in (("tour", graph(s, d, "geo_tree"), 4.0), ("flood", generators.path(s, 48), 2.0), ("diameter", generators.star(s, 32), 4.0), ("hook", generators.path(s, 64), 4.0)):
        x = certificate(ledger_of(algo, g), g.vertices.count(), c)
        rows.append((algo, x.storage_ok, x.compute_ok, x.messages_ok, x.rounds_ok, x.storage_ratio, x.storage_witness, x.compute_ratio, x.compute_witness, x.worst_ratio, x.witness))
    return s.createDataFrame(rows, "algo string, storage_ok boolean, compute_ok boolean, messages_ok boolean, rounds_ok boolean, storage_ratio double, storage_witness long, compute_ratio double, compute_witness long, message_ratio double, message_witness long")


add("balance_verdicts", balance_verdicts)
# Harder workloads ---------------------------------------------------------------------------------------------------
TRI = "with {e} select a.src as x, a.dst as y, b.dst as z from e a join e b on a.dst = b.src join e c on c.src = a.src and c.dst = b.dst where a.src < a.dst and a.dst < b.dst"
add("knn_edges", lambda s, d: frame(s, d, "embed_knn"), duck("embed_knn"))
add("triangles_embed", lambda s, d: subgraph.triangles(graph(s, d, "embed_knn")), TRI.format(e=oracles.sym("embed_knn")))
add("triangles_user_hop", lambda s, d: subgraph.triangles(graph(s, d, "user_hop")), TRI.format(e=oracles.sym("user_hop")))
add("clustering_user_hop", lambda s, d: subgraph.clustering_coefficient(graph(s, d, "user_hop")).select("id", "triangles", F.round("coefficient", 9).alias("coefficient")), f"with t as ({TRI.format(e=oracles.sym('user_hop'))}), u as (select unnest([x, y, z]) as id from t), n as (select id, count(*) as k from u group by id), dg as (with {oracles.sym('user_hop')} select src as id, count(*) as d from e group by src) select dg.id, coalesce(k, 0) as triangles, round(case when d < 2 then 0.0 else 2.0 * coalesce(k, 0) / (d * (d - 1)) end, 9)::double as coefficient from dg left join n on n.id = dg.id")
add("motif3_user_hop", lambda s, d: subgraph.motif3(graph(s, d, "user_hop")), f"with t as ({TRI.format(e=oracles.sym('user_hop'))}), k as (with {oracles.sym('user_hop')} select count(*) as d from e group by src) select 'triangle' as motif, (select count(*) from t) as n union all select 'wedge', (sum(d * (d - 1) / 2) - 3 * (select count(*) from t))::bigint from k")
add("match_pattern_turns", lambda s, d: subgraph.match_pattern(*TALK, turns(s, d)), f"with g as ({duck('turns')}), l as ({duck('turn_labels')}) select a.src as v0, a.dst as v1, b.dst as v2 from g a join g b on a.dst = b.src join l x on x.id = a.src and x.label = 'user' join l y on y.id = a.dst and y.label = 'assistant' join l z on z.id = b.dst and z.label = 'user'")
add("link_scores_user_hop", lambda s, d: subgraph.link_scores(graph(s, d, "user_hop")).select("src", "dst", "common", F.round("jaccard", 9).alias("jaccard")), f"with {oracles.sym('user_hop')}, dg as (select src, count(*) as d from e group by src), p as (select a.dst as x, b.dst as y, count(*) as common from e a join e b on a.src = b.src where a.dst < b.dst group by 1, 2) select x as src, y as dst, common, round(common / (da.d + db.d - common), 9) as jaccard from p join dg da on da.src = x join dg db on db.src = y where not exists (select 1 from e where e.src = x and e.dst = y)")
add("communities_user_hop", lambda s, d: subgraph.label_communities(graph(s, d, "user_hop")))
add("modularity_geo", lambda s, d: subgraph.modularity(graph(s, d, "geo_tree"), graph(s, d, "geo_tree").vertices.select("id", F.lit(0).cast("long").alias("community"))).select(F.round("modularity", 9).alias("modularity")), "select 0.0::double as modularity")
add("partition_cut_supply_thin", lambda s, d: subgraph.partition_quality(graph(s, d, "supply_thin"), graph(s, d, "supply_thin").vertices.select("id", F.pmod("id", F.lit(4)).alias("part"))).select("cut_edges", "edges"), f"select count(*) filter (where src % 4 <> dst % 4) as cut_edges, count(*) as edges from ({duck('supply_thin')}) as g")


def partition_by_labels(s: SparkSession, d: str) -> DataFrame:
    """Vertices placed, and whether fewer edges are cut than by the random split that it starts from."""
    g = graph(s, d, "supply_thin")
    first, last = (subgraph.label_partition(g, 4, rounds=n) for n in (0, 8))
    cut = [subgraph.partition_quality(g, p).select(F.col("cut_edges").alias(k)) for p, k in ((first, "a"), (last, "b"))]
    return last.agg(F.count_distinct("id").alias("vertices")).crossJoin(cut[0]).crossJoin(cut[1]).select("vertices", (F.col("b") < F.col("a")).alias("fewer"))


add("label_partition_supply_thin", partition_by_labels, f"with {oracles.sym('supply_thin')} select count(*) as vertices, true as fewer from v")
add("spectral_supply_forest", lambda s, d: subgraph.spectral_coords(graph(s, d, "user_hop"), 8))


def efficiency_table(s: SparkSession, d: str) -> DataFrame:
    """Measured products against sequential operations on the given graphs, at one size; both sides of link ranking make
    ``RANK_ROUNDS`` rounds. Neither the growth over sizes nor the verdict on more work is part of it; README lists the methods that
    are missing. Each graph is written once, not derived anew for every look at it."""
    rows, rounds, held = [], Rounds(s), {}
    for algo, name, base in (("flood", "supply_forest", seq.components), ("hook", "supply_forest", seq.components), ("tour", "geo_tree", seq.tree_orders), ("pagerank", "supply_thin", seq.power_iteration), ("diameter", "user_hop", seq.hops)):
        if name not in held:
            made = graph(s, d, name)
            held[name] = replace(made, vertices=rounds.cut(made.vertices)[0], edges=rounds.cut(made.edges)[0])
        g = held[name]
        led = ledger_of(algo, g)
        ops = seq.operations(g, base, **({"iters": RANK_ROUNDS} if base is seq.power_iteration else {}))
        product = time_processor_product(led.table(s)).first().product
        cert = certificate(led, g.vertices.count())
        rows.append((algo, led.rounds, led.messages, sum(led.combined), float(product), int(ops), float(product) / ops, cert.balanced))
    return s.createDataFrame(rows, "algo string, rounds long, messages long, combined long, product double, sequential long, ratio double, balanced boolean")


add("efficiency_table", efficiency_table)
for key, (query, sql) in (relational.ALL | reports.ALL).items():
    add(key, query, sql)


def queries() -> dict[str, Query]:
    return {k: q for k, (q, _) in ALL.items()}


def oracle_sql() -> dict[str, str]:
    return {k: sql for k, (_, sql) in ALL.items() if sql}


__all__ = ["SQL", "frame", "oracle_sql", "queries"]
