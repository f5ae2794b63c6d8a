"""Graph, dual and strong simulation of a small query graph."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..engine import Rounds
from ..model import Graph

#: A query graph of more edges than this is refused: it goes to every executor.
MAX_QUERY = 1000


def _settle(rounds: Rounds, match: DataFrame, arcs: DataFrame, q_edges: list, keys: list[str], both: bool) -> DataFrame:
    """The greatest relation inside match (keys..., q, id) in which every pair has what its query edges ask for."""
    if len(q_edges) > MAX_QUERY:
        raise ValueError(f"more than {MAX_QUERY} query edges")
    spark = match.sparkSession
    labelled = "elabel" in arcs.columns
    qe = F.broadcast(spark.createDataFrame([(a, b, x[0] if x else None) for a, b, *x in q_edges], "qa int, qb int, ql string")) if q_edges else None
    while qe is not None:
        rounds.next()
        fits = F.lit(True) if not labelled else (F.col("ql").isNull() | (F.col("ql") == F.col("elabel")))

        def kept(match: DataFrame, forward: bool) -> DataFrame:
            near, far, qn, qf = ("src", "dst", "qa", "qb") if forward else ("dst", "src", "qb", "qa")
            other = match.select(*keys, F.col("q").alias(qf), F.col("id").alias(far))
            on = [k for k in keys if k in arcs.columns]
            held = other.join(arcs, [far, *on]).join(qe, qf).where(fits).select(*keys, F.col(qn).alias("q"), F.col(near).alias("id"), "qa", "qb").distinct()
            have = held.groupBy(*keys, "q", "id").agg(F.count("*").alias("have"))
            need = qe.groupBy(F.col(qn).alias("q")).agg(F.count("*").alias("need"))
            return match.join(F.broadcast(need), "q", "left").join(have, [*keys, "q", "id"], "left").where("need is null or have = need").select(*keys, "q", "id")

        new = kept(match, True)
        if both:
            new, _ = rounds.cut(new)
            new = kept(new, False)
        before = match.count()
        match, got = rounds.cut(new, match, n=F.count(F.lit(1)))
        if got["n"] == before:
            break
    return match


def _candidates(q_labels: dict[int, str], g: Graph) -> DataFrame:
    q = g.spark.createDataFrame(list(q_labels.items()), "q int, label string")
    return g.vertices.join(F.broadcast(q), "label").select("q", "id")


def _total(match: DataFrame, q_labels: dict[int, str], keys: list[str]) -> DataFrame:
    """Nothing, of the whole or of a key, if a query vertex has no match."""
    if keys:
        full = match.groupBy(*keys).agg(F.count_distinct("q").alias("n")).where(F.col("n") == len(q_labels))
        return match.join(full, keys, "left_semi")
    full = match.agg(F.count_distinct("q").alias("n")).where(F.col("n") == len(q_labels))
    return match.join(F.broadcast(full), F.lit(True), "left_semi")


def graph_simulation(q_labels: dict[int, str], q_edges: list, g: Graph, require_total: bool = True, dual: bool = False) -> DataFrame:
    """(q, id): the greatest relation under which labels agree and every query edge of q has an edge of id to a match;
    ``dual``: edges into q as well. ``q_edges``: (from, to) or (from, to, edge label)."""
    rounds = Rounds(g.spark)
    arcs, _ = rounds.cut(g.edges.select("src", "dst", *[c for c in g.edges.columns if c == "elabel"]).distinct())
    match, _ = rounds.cut(_candidates(q_labels, g))
    match = _settle(rounds, match, arcs, q_edges, [], dual)
    return _total(match, q_labels, []) if require_total else match


def dual_simulation(q_labels: dict[int, str], q_edges: list, g: Graph, require_total: bool = True) -> DataFrame:
    return graph_simulation(q_labels, q_edges, g, require_total, dual=True)


def query_diameter(q_labels: dict[int, str], q_edges: list) -> int:
    """Longest shortest path of the query graph without regard to direction."""
    near = {q: {q} for q in q_labels}
    for a, b, *_ in q_edges:
        near[a].add(b)
        near[b].add(a)
    most = 0
    for q in q_labels:
        seen, front, hop = {q}, {q}, 0
        while front := {y for x in front for y in near[x]} - seen:
            hop += 1
            seen |= front
        most = max(most, hop)
    return most


def strong_simulation(q_labels: dict[int, str], q_edges: list, g: Graph, radius: int | None = None) -> DataFrame:
    """(center, q, id): dual simulation inside the ball around each centre, cut to the part connected with the centre by
    edges that realise a query edge. Centres and balls are cut to what dual simulation of the whole leaves."""
    rounds = Rounds(g.spark)
    radius = query_diameter(q_labels, q_edges) if radius is None else radius
    whole, _ = rounds.cut(dual_simulation(q_labels, q_edges, g))
    arcs, _ = rounds.cut(g.edges.select("src", "dst", *[c for c in g.edges.columns if c == "elabel"]).distinct())
    both, _ = rounds.cut(arcs.select("src", "dst").union(arcs.select("dst", "src")).distinct())
    ball, _ = rounds.cut(whole.select(F.col("id").alias("center"), "id").distinct())
    front = ball
    for _ in range(radius):
        new = front.join(both, front["id"] == both["src"]).select("center", F.col("dst").alias("id")).distinct().join(ball, ["center", "id"], "left_anti")
        front, _ = rounds.cut(new)
        ball = ball.unionByName(front)
    match, _ = rounds.cut(ball.join(whole, "id").select("center", "q", "id"))
    match = _total(_settle(rounds, match, arcs, q_edges, ["center"], True), q_labels, ["center"])
    match, _ = rounds.cut(match)
    qe = F.broadcast(g.spark.createDataFrame([(a, b) for a, b, *_ in q_edges], "qa int, qb int"))
    a, b = match.select("center", F.col("q").alias("qa"), F.col("id").alias("src")), match.select("center", F.col("q").alias("qb"), F.col("id").alias("dst"))
    real = a.join(qe, "qa").join(arcs, "src").join(b, ["center", "qb", "dst"]).select("center", "src", "dst")
    real, _ = rounds.cut(real.union(real.select("center", "dst", "src")).distinct())
    hit, _ = rounds.cut(match.where("center = id").select("center", "id").distinct())
    front = hit
    while True:
        rounds.next()
        new = front.withColumnRenamed("id", "src").join(real, ["center", "src"]).select("center", F.col("dst").alias("id")).distinct().join(hit, ["center", "id"], "left_anti")
        front, got = rounds.cut(new, n=F.count(F.lit(1)))
        if not got["n"]:
            break
        hit = hit.unionByName(front)
    return match.join(hit, ["center", "id"], "left_semi").select("center", "q", "id")
