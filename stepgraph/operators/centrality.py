"""Betweenness, by hops or by weights."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..engine import Rounds, count_if
from ..model import Graph
from . import batched
from .flood import shortest_paths


def _dependencies_by_rounds(g: Graph, start: DataFrame) -> DataFrame:
    """(id, delta), a row a source and vertex; every level is written."""
    rounds = Rounds(g.spark)
    arcs, _ = rounds.cut(g.simple().arcs().select("src", "dst"))
    level, _ = rounds.cut(start.select(F.col("id").alias("source"), "id", F.lit(1.0).alias("sigma"), F.lit(0).alias("level")))
    levels, seen = [level], level
    while True:
        hop = rounds.next()
        mail = level.join(arcs, level["id"] == arcs["src"]).groupBy("source", F.col("dst").alias("id")).agg(F.sum("sigma").alias("sigma"))
        level, got = rounds.cut(mail.join(seen, ["source", "id"], "left_anti").withColumn("level", F.lit(hop)), n=F.count(F.lit(1)))
        if not got["n"]:
            break
        levels.append(level)
        seen = seen.unionByName(level)
    below = None
    total = None
    for level in reversed(levels):
        if below is None:
            below, _ = rounds.cut(level.select("source", "id", "sigma", F.lit(0.0).alias("delta")))
        else:
            part = below.select("source", F.col("id").alias("dst"), ((1 + F.col("delta")) / F.col("sigma")).alias("x"))
            got = part.join(arcs, "dst").groupBy("source", F.col("src").alias("id")).agg(F.sum("x").alias("x"))
            below, _ = rounds.cut(level.join(got, ["source", "id"], "left").select("source", "id", "sigma", (F.col("sigma") * F.coalesce("x", F.lit(0.0))).alias("delta")))
        one = below.where("source <> id").select("id", "delta")
        total = one if total is None else total.unionByName(one)
    return total


def betweenness(g: Graph, sources: DataFrame | None = None, normalized: bool = False) -> DataFrame:
    """(id, score). Levels and path counts of a flood from each source; then dependencies from the deepest level back, in tasks
    that hold the graph, or by rounds where it is too large. The graph is written once, not derived anew for every look at it. With
    ``sources`` (id), the sum over these is scaled to all."""
    rounds = Rounds(g.spark)
    g = replace(g, vertices=rounds.cut(g.vertices)[0], edges=rounds.cut(g.edges)[0])
    start = (g.vertices if sources is None else sources).select("id")
    if (held := batched.hold(g, sources)) is not None:
        sums = batched.dependencies(g, held)
    else:
        sums = _dependencies_by_rounds(g, start).groupBy("id").agg(F.sum("delta").alias("d"))
    n = g.vertices.count()
    scale = (1.0 if g.directed else 0.5) * (n / max(1, start.count()) if sources is not None else 1.0)
    if normalized and n > 2:
        scale *= (1.0 if g.directed else 2.0) / ((n - 1) * (n - 2))
    return g.vertices.select("id").join(sums, "id", "left").select("id", (F.coalesce("d", F.lit(0.0)) * scale).alias("score"))


def weighted_betweenness(g: Graph, sources: DataFrame | None = None, digits: int = 9) -> DataFrame:
    """(id, score) over shortest paths by weight, which must be above 0. An arc lies on one if the distances of its ends differ
    by its weight, to ``digits``. Path counts, then dependencies, are summed along these arcs again until none changes, which
    takes as many rounds as a shortest path has arcs. With ``sources`` (id), the sum over these is scaled to all."""
    if g.edges.where("w is null or not w > 0").limit(1).count():
        raise ValueError("weights must be above 0")
    rounds = Rounds(g.spark)
    start = (g.vertices if sources is None else sources).select("id")
    far, _ = rounds.cut(shortest_paths(g, start).select("source", "id", "dist"))
    a, b = (far.select("source", F.col("id").alias(k), F.col("dist").alias(f"d{k}")) for k in ("src", "dst"))
    on, _ = rounds.cut(a.join(g.simple().arcs(), "src").join(b, ["source", "dst"]).where(F.round(F.col("dsrc") + F.col("w") - F.col("ddst"), digits) == 0).select("source", "src", "dst"))

    def settled(begin: DataFrame, term: Callable[[DataFrame], DataFrame], end: str, value: str, first: Column) -> DataFrame:
        state, _ = rounds.cut(begin)
        while True:
            rounds.next()
            got = term(state).groupBy("source", F.col(end).alias("id")).agg(F.sum("x").alias("x"))
            new = state.join(got, ["source", "id"], "left").withColumn("new", first + F.coalesce("x", F.lit(0.0)))
            new, seen = rounds.cut(new.withColumns({"changed": F.col("new") != F.col(value), value: F.col("new")}).drop("x", "new"), state, n=count_if(F.col("changed")))
            state = new
            if not seen["n"]:
                return state.drop("changed")
            state = state.drop("changed")

    own = F.when(F.col("source") == F.col("id"), 1.0).otherwise(0.0)
    sigma = settled(far.select("source", "id", own.alias("sigma")), lambda s: on.join(s.withColumnRenamed("id", "src"), ["source", "src"]).select("source", "dst", F.col("sigma").alias("x")), "dst", "sigma", own)
    n, _ = rounds.cut(sigma)
    above = n.select("source", F.col("id").alias("src"), F.col("sigma").alias("s"))
    pull = lambda s: on.join(s.withColumnRenamed("id", "dst"), ["source", "dst"]).join(above, ["source", "src"]).select("source", "src", (F.col("s") / F.col("sigma") * (1 + F.col("delta"))).alias("x"))
    delta = settled(n.withColumn("delta", F.lit(0.0)), pull, "src", "delta", F.lit(0.0))
    scale = (1.0 if g.directed else 0.5) * (g.vertices.count() / max(1, start.count()) if sources is not None else 1.0)
    sums = delta.where("source <> id").groupBy("id").agg(F.sum("delta").alias("d"))
    return g.vertices.select("id").join(sums, "id", "left").select("id", (F.coalesce("d", F.lit(0.0)) * scale).alias("score"))
