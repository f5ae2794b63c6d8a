"""Triangles, clustering, motifs, small patterns, link scores, communities and other harder workloads."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..engine import Rounds, count_if
from ..functions.coins import draw, unit
from ..model import Graph


def oriented(g: Graph) -> DataFrame:
    """(a, b): every edge once, from the end of lower degree; so no vertex has more than about sqrt(2m) of them."""
    s = g.symmetrized()
    d = s.degrees()
    x, y = (d.select(F.col("id").alias(k), F.col("degree").alias(f"d{k}")) for k in ("src", "dst"))
    e = s.edges.select("src", "dst").join(x, "src").join(y, "dst")
    low = (F.col("dsrc") < F.col("ddst")) | ((F.col("dsrc") == F.col("ddst")) & (F.col("src") < F.col("dst")))
    return e.select(F.when(low, F.col("src")).otherwise(F.col("dst")).alias("a"), F.when(low, F.col("dst")).otherwise(F.col("src")).alias("b"))


def triangles(g: Graph) -> DataFrame:
    """(x, y, z), x < y < z."""
    e, _ = Rounds(g.spark).cut(oriented(g))
    wedge = e.select("a", F.col("b").alias("u")).join(e.select("a", F.col("b").alias("v")), "a").where("u <> v")
    closed = wedge.join(e.select(F.col("a").alias("u"), F.col("b").alias("v")), ["u", "v"])
    t = F.array_sort(F.array("a", "u", "v"))
    return closed.select(t[0].alias("x"), t[1].alias("y"), t[2].alias("z"))


def clustering_coefficient(g: Graph) -> DataFrame:
    """(id, triangles, coefficient); 0 where the degree is below two."""
    t = triangles(g)
    n = t.select(F.explode(F.array("x", "y", "z")).alias("id")).groupBy("id").agg(F.count("*").alias("triangles"))
    d = g.symmetrized().degrees().join(n, "id", "left").fillna(0, ["triangles"])
    k = F.col("degree")
    return d.select("id", "triangles", F.when(k < 2, 0.0).otherwise(2.0 * F.col("triangles") / (k * (k - 1))).alias("coefficient"))


def motif3(g: Graph) -> DataFrame:
    """(motif, n): open wedges and triangles."""
    t = triangles(g).count()
    d = g.symmetrized().degrees()
    wedges = d.agg(F.coalesce(F.sum(F.col("degree") * (F.col("degree") - 1) / 2), F.lit(0.0)).cast("long").alias("n"))
    return wedges.select(F.lit("wedge").alias("motif"), (F.col("n") - 3 * t).alias("n")).union(g.spark.createDataFrame([("triangle", t)], "motif string, n long"))


def match_pattern(q_labels: dict[int, str], q_edges: list, g: Graph) -> DataFrame:
    """Columns v0, v1, ...: injective matches of a small connected pattern, joined edge by edge."""
    arcs, out, done = g.edges.select("src", "dst").distinct(), None, set()
    todo = list(q_edges)
    of = lambda q: g.vertices.where(F.col("label") == q_labels[q]).select(F.col("id").alias(f"v{q}"))
    while todo:
        a, b = next((e for e in todo if e[0] in done or e[1] in done), todo[0])[:2]
        todo.remove(next(e for e in todo if e[:2] == (a, b)))
        e = arcs.select(F.col("src").alias(f"v{a}"), F.col("dst").alias(f"v{b}")).join(of(a), f"v{a}", "left_semi").join(of(b), f"v{b}", "left_semi")
        out = e if out is None else out.join(e, [f"v{q}" for q in (a, b) if q in done])
        for q in (a, b):
            if q not in done:
                for other in done:
                    out = out.where(F.col(f"v{q}") != F.col(f"v{other}"))
                done.add(q)
    return out


def link_scores(g: Graph) -> DataFrame:
    """(src, dst, common, jaccard, rare) of unlinked pairs with a common neighbour; ``rare`` weighs it by 1 / log(degree)."""
    s = g.symmetrized()
    arcs, d = s.arcs().select("src", "dst"), s.degrees()
    w = arcs.join(d.select(F.col("id").alias("src"), (1 / F.log("degree")).alias("x")), "src")
    pairs = w.select("src", F.col("dst").alias("a"), "x").join(arcs.select("src", F.col("dst").alias("b")), "src").where("a < b")
    got = pairs.groupBy("a", "b").agg(F.count("*").alias("common"), F.sum("x").alias("rare"))
    got = got.join(s.edges.select(F.col("src").alias("a"), F.col("dst").alias("b")), ["a", "b"], "left_anti")
    da, db = (d.select(F.col("id").alias(k), F.col("degree").alias(f"d{k}")) for k in ("a", "b"))
    return got.join(da, "a").join(db, "b").select(F.col("a").alias("src"), F.col("b").alias("dst"), "common", (F.col("common") / (F.col("da") + F.col("db") - F.col("common"))).alias("jaccard"), "rare")


def label_communities(g: Graph, rounds: int = 5) -> DataFrame:
    """(id, community): each vertex takes the label that most of its neighbours have, the least of equals; odd and even ids in turn."""
    r = Rounds(g.spark)
    arcs, _ = r.cut(g.symmetrized().arcs().select("src", "dst"))
    state, _ = r.cut(g.vertices.select("id", F.col("id").alias("community")))
    for k in range(2 * rounds):
        votes = arcs.join(state.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id"), "community").agg(F.count("*").alias("n"))
        best = votes.groupBy("id").agg(F.max(F.struct("n", (-F.col("community")).alias("c"))).alias("m")).select("id", (-F.col("m.c")).alias("new"))
        now = F.when((F.pmod("id", F.lit(2)) == k % 2) & F.col("new").isNotNull(), F.col("new")).otherwise(F.col("community"))
        state, _ = r.cut(state.join(best, "id", "left").select("id", now.alias("community")), state)
    return state


def modularity(g: Graph, communities: DataFrame) -> DataFrame:
    """(modularity) of (id, community)."""
    s = g.symmetrized()
    m = s.edges.count()
    a, b = (communities.select(F.col("id").alias(k), F.col("community").alias(f"c{k}")) for k in ("src", "dst"))
    inside = s.edges.join(a, "src").join(b, "dst").where("csrc = cdst").groupBy(F.col("csrc").alias("community")).agg(F.count("*").alias("e"))
    total = s.degrees().join(communities, "id").groupBy("community").agg(F.sum("degree").alias("k"))
    x = total.join(inside, "community", "left").fillna(0, ["e"])
    return x.agg(F.sum(F.col("e") / m - F.pow(F.col("k") / (2.0 * m), F.lit(2))).alias("modularity"))


def influence_greedy(g: Graph, k: int, chance: float = 0.1, samples: int = 8, seed: int = 1) -> list[int]:
    """k seeds by greedy coverage of components in fixed samples of live edges."""
    from .components import hook_shortcut

    r, reached = Rounds(g.spark), None
    edge = F.col("src") * 31 + F.col("dst")
    for s in range(samples):
        live = g.symmetrized().edges.where(unit(edge, seed, s) < chance)
        part = hook_shortcut(Graph(g.vertices.select("id"), live)).select("id", F.col("component"), F.lit(s).alias("sample"))
        reached = part if reached is None else reached.unionByName(part)
    reached, _ = r.cut(reached)
    chosen: list[int] = []
    for _ in range(k):
        sizes = reached.groupBy("sample", "component").agg(F.count("*").alias("n"))
        best = reached.join(sizes, ["sample", "component"]).groupBy("id").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "id").first()
        if best is None:
            break
        chosen.append(best.id)
        gone = reached.where(F.col("id") == best.id).select("sample", "component")
        reached, _ = r.cut(reached.join(gone, ["sample", "component"], "left_anti"))
    return chosen


def partition_quality(g: Graph, parts: DataFrame) -> DataFrame:
    """(cut_edges, edges, balance) of (id, part)."""
    a, b = (parts.select(F.col("id").alias(k), F.col("part").alias(f"p{k}")) for k in ("src", "dst"))
    e = g.symmetrized().edges.join(a, "src").join(b, "dst").agg(count_if(F.col("psrc") != F.col("pdst")).alias("cut_edges"), F.count("*").alias("edges"))
    size = parts.groupBy("part").count().agg((F.max("count") / F.avg("count")).alias("balance"))
    return e.crossJoin(F.broadcast(size))


def label_partition(g: Graph, parts: int, rounds: int = 8, seed: int = 1) -> DataFrame:
    """(id, part): from a random split, a vertex wants the part that most of its neighbours are in. Of those that want to change
    from one part to another, about half as many go as want to come back, by a draw, so sizes stay near equal. The split
    that cut the fewest edges is returned."""
    r = Rounds(g.spark)
    arcs, _ = r.cut(g.symmetrized().arcs().select("src", "dst"))
    state, _ = r.cut(g.vertices.select("id", F.pmod(draw(F.col("id"), seed), F.lit(parts)).cast("int").alias("part")))
    best, least = state, None
    for k in range(rounds + 1):
        votes = arcs.join(state.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id"), F.col("part").alias("p")).agg(F.count("*").alias("n"))
        wish = votes.join(state, "id").groupBy("id").agg(F.max(F.struct("n", (-F.col("p")).alias("p"))).alias("m"), F.sum(F.when(F.col("p") == F.col("part"), F.col("n")).otherwise(0)).alias("own"), F.sum("n").alias("all"))
        wish = wish.withColumn("want", F.when(F.col("m.n") > F.col("own"), -F.col("m.p")))
        wish, got = r.cut(state.join(wish, "id", "left").select("id", "part", "want", F.coalesce(F.col("all") - F.col("own"), F.lit(0)).alias("cut")), cut=F.sum("cut"))
        if least is None or got["cut"] < least:
            best, least = state, got["cut"]
        if k == rounds:
            return best
        # at most parts * parts rows
        flow = wish.where("want is not null").groupBy("part", "want").agg(F.count("*").alias("go"))
        back = flow.select(F.col("part").alias("want"), F.col("want").alias("part"), F.col("go").alias("come"))
        share = flow.join(back, ["part", "want"]).select("part", "want", (F.least("go", "come") / F.col("go") / 2).alias("share"))
        moves = F.coalesce(unit(F.col("id"), seed, k + 1) < F.col("share"), F.lit(False))
        state, _ = r.cut(wish.join(F.broadcast(share), ["part", "want"], "left").select("id", F.when(moves, F.col("want")).otherwise(F.col("part")).alias("part")))
    return best


def spectral_coords(g: Graph, iters: int = 20) -> DataFrame:
    """(id, x): the second direction of the lazy walk, by power iteration with the first one taken out."""
    r = Rounds(g.spark)
    s = g.symmetrized()
    d = s.degrees()
    arcs, _ = r.cut(s.arcs().select("src", "dst"))
    state, _ = r.cut(d.select("id", "degree", (unit(F.col("id"), 5) - 0.5).alias("x")))
    for _ in range(iters):
        mean = state.agg((F.sum(F.col("x") * F.col("degree")) / F.sum("degree")).alias("m"), F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("n")).first()
        norm = mean.n or 1.0
        flat = state.select("id", "degree", ((F.col("x") - mean.m) / norm).alias("x"))
        got = arcs.join(flat.select(F.col("id").alias("src"), "x"), "src").groupBy(F.col("dst").alias("id")).agg(F.avg("x").alias("y"))
        state, _ = r.cut(flat.join(got, "id", "left").select("id", "degree", ((F.col("x") + F.coalesce("y", "x")) / 2).alias("x")), state)
    return state.select("id", "x")
