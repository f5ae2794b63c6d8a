"""Independent sets, colouring and matching."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..engine import Rounds, count_if
from ..functions.coins import draw, unit
from ..model import Graph


def _independent(rounds: Rounds, free: DataFrame, arcs: DataFrame, rule: str, seed: int, colour: int) -> DataFrame:
    """(id) of a maximal independent set of ``free`` (id) under arcs between free vertices. A neighbour of a winner sits out."""
    won, live, n = None, free, 1
    while n:
        step = rounds.next()
        a = arcs.join(live.withColumnRenamed("id", "src"), "src", "left_semi").join(live.withColumnRenamed("id", "dst"), "dst", "left_semi")
        deg = a.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("d"), F.min("dst").alias("least"))
        x = live.join(deg, "id", "left")
        if rule == "lexi":
            new = x.where("d is null or id < least")
        else:
            x, _ = rounds.cut(x.withColumn("try", F.col("d").isNull() | (unit(F.col("id"), seed, colour, step) < 1 / (2 * F.col("d")))))
            tried = x.where("try and d is not null").select(F.col("id").alias("src"))
            near = a.join(tried, "src", "left_semi").groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("m"))
            new = x.where("try").join(near, "id", "left").where("d is null or m is null or m > id")
        new, _ = rounds.cut(new.select("id"))
        won = new if won is None else won.union(new)
        out = a.join(new.withColumnRenamed("id", "src"), "src", "left_semi").select(F.col("dst").alias("id")).union(new)
        live, got = rounds.cut(live.join(out, "id", "left_anti"), n=F.count(F.lit(1)))
        n = got["n"]
    return won


def maximal_independent_set(g: Graph, seed: int = 1, rule: str = "random") -> DataFrame:
    """(id, in_mis). "random": a vertex stands with probability 1 / (2 degree), the smallest of standing neighbours wins;
    "lexi": one wins that is smaller than all its neighbours, which gives the set that a scan by id finds."""
    rounds = Rounds(g.spark)
    arcs, _ = rounds.cut(g.symmetrized().arcs().select("src", "dst"))
    won = _independent(rounds, rounds.cut(g.vertices.select("id"))[0], arcs, rule, seed, 0)
    return g.vertices.select("id").join(won.withColumn("in_mis", F.lit(True)), "id", "left").fillna(False, ["in_mis"])


def mis_coloring(g: Graph, seed: int = 1, rule: str = "random") -> DataFrame:
    """(id, color), colours from 0: one maximal independent set of what is left after another."""
    rounds = Rounds(g.spark)
    arcs, _ = rounds.cut(g.symmetrized().arcs().select("src", "dst"))
    free, got = rounds.cut(g.vertices.select("id"), n=F.count(F.lit(1)))
    out, colour = free.select("id", F.lit(0).alias("color")).limit(0), 0
    while got["n"]:
        won, _ = rounds.cut(_independent(rounds, free, arcs, rule, seed, colour))
        out = out.unionByName(won.withColumn("color", F.lit(colour)))
        free, got = rounds.cut(free.join(won, "id", "left_anti"), n=F.count(F.lit(1)))
        arcs, _ = rounds.cut(arcs.join(free.withColumnRenamed("id", "src"), "src", "left_semi").join(free.withColumnRenamed("id", "dst"), "dst", "left_semi"))
        colour += 1
    return out


def dominant_edge_matching(g: Graph) -> DataFrame:
    """(src, dst, w): every free vertex points along its heaviest edge to a free one; two that point at each other match."""
    rounds = Rounds(g.spark)
    s = g.simple()
    arcs, got = rounds.cut(s.arcs().withColumns({"u": F.least("src", "dst"), "v": F.greatest("src", "dst")}), n=F.count(F.lit(1)))
    out = arcs.select("src", "dst", "w").limit(0)
    while got["n"]:
        rounds.next()
        # of equal weights the edge with the smaller ends is the heavier one
        best = arcs.groupBy("src").agg(F.max(F.struct("w", (-F.col("u")).alias("a"), (-F.col("v")).alias("b"), "dst")).alias("m")).select("src", "m.dst", "m.w")
        back = best.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
        pairs, _ = rounds.cut(best.join(back, ["src", "dst"], "left_semi").where("src < dst"))
        out = out.unionByName(pairs)
        taken = pairs.select(F.col("src").alias("t")).union(pairs.select("dst"))
        arcs, got = rounds.cut(arcs.join(taken, arcs["src"] == taken["t"], "left_anti").join(taken, F.col("dst") == taken["t"], "left_anti"), arcs, n=F.count(F.lit(1)))
    return out


def bipartite_matching(g: Graph, seed: int = 1, rule: str = "random") -> DataFrame:
    """(left, right) of edges (src on the left, dst on the right): left ones ask, right ones grant one, left ones accept one."""
    rounds = Rounds(g.spark)
    e, got = rounds.cut(g.edges.select("src", "dst").distinct(), n=F.count(F.lit(1)))
    out = e.select(F.col("src").alias("left"), F.col("dst").alias("right")).limit(0)
    while got["n"]:
        step = rounds.next()
        by = (lambda c: F.struct(draw(F.col(c), seed, step).alias("o"), F.col(c).alias("x"))) if rule == "random" else (lambda c: F.struct(F.col(c).alias("o"), F.col(c).alias("x")))
        granted = e.groupBy("dst").agg(F.min(by("src")).alias("m")).select("dst", F.col("m.x").alias("src"))
        pairs, _ = rounds.cut(granted.groupBy("src").agg(F.min(by("dst")).alias("m")).select("src", F.col("m.x").alias("dst")))
        out = out.unionByName(pairs.select(F.col("src").alias("left"), F.col("dst").alias("right")))
        e, got = rounds.cut(e.join(pairs.select("src"), "src", "left_anti").join(pairs.select("dst"), "dst", "left_anti"), e, n=F.count(F.lit(1)))
    return out


def improper_edges(g: Graph, colours: DataFrame) -> DataFrame:
    """(n) of edges whose ends have one colour."""
    a, b = (colours.select(F.col("id").alias(k), F.col("color").alias(f"c{k}")) for k in ("src", "dst"))
    return g.simple().edges.join(a, "src").join(b, "dst").agg(count_if(F.col("csrc") == F.col("cdst")).alias("n"))
