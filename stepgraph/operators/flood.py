"""Floods: hop distances, eccentricity and diameter, minimum labels, shortest paths, reachability."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..cost import Ledger
from ..engine import Rounds, count_if
from ..model import Graph
from . import batched


def all_pairs_hops(g: Graph, sources: DataFrame | None = None, max_hops: int | None = None, max_pairs: int = 50_000_000, ledger: Ledger | None = None) -> DataFrame:
    """(src, dst, hops) of every pair that is connected, or of those from ``sources`` (id). The history of a flood of ids is
    this table; it has up to n * n rows. A graph that a worker can hold is flooded there and its rows are handed on as they are
    made. Of a larger one they are stored by rounds, so above ``max_pairs`` this raises: give sources, in batches if need be."""
    if (held := batched.hold(g, sources, incoming=True)) is not None:
        if ledger:
            _record_hops(g, batched.arrivals(g, held, None if max_hops is None else max_hops - 1), ledger)
        return batched.pairs(g, held, max_hops)
    rounds = Rounds(g.spark, ledger)
    arcs, _ = rounds.cut(g.simple().arcs().select(F.col("src").alias("via"), F.col("dst").alias("to")))
    start = (g.vertices if sources is None else sources).select("id").distinct()
    front, _ = rounds.cut(start.select(F.col("id").alias("src"), F.col("id").alias("dst"), F.lit(0).alias("hops")))
    last, seen, total = front.limit(0), front, 0
    degrees = rounds.cut(g.degrees())[0] if ledger else None
    while max_hops is None or rounds.step < max_hops:
        hop = rounds.next()
        mail = front.join(arcs, front["dst"] == arcs["via"])
        if ledger:
            sent = ledger.record(hop - 1, mail.select(F.col("via").alias("src"), F.col("to").alias("dst")), degrees, stored=seen.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("n")))
            if not sent:
                break
        # Where arcs go both ways, a neighbour of what is ``hop - 1`` away is at least ``hop - 2`` away.
        known = seen if g.directed else last.unionByName(front)
        new = mail.select("src", F.col("to").alias("dst")).distinct().join(known, ["src", "dst"], "left_anti").withColumn("hops", F.lit(hop))
        last = front
        front, got = rounds.cut(new, n=F.count(F.lit(1)))
        total += got["n"]
        if not got["n"]:
            break
        if total > max_pairs:
            raise ValueError(f"more than {max_pairs} pairs: give sources, or raise max_pairs")
        seen = seen.unionByName(front)
    return seen


def _record_hops(g: Graph, arrivals: DataFrame, ledger: Ledger) -> None:
    """The costs of a hop flood by rounds, from how many ids (id, hop, n) arrive where and when: each goes on along all arcs."""
    rounds = Rounds(g.spark)
    arcs, _ = rounds.cut(g.simple().arcs().select("src", "dst"))
    arrivals, got = rounds.cut(arrivals, last=F.max("hop"))
    degrees, _ = rounds.cut(g.degrees())
    # The sums of each vertex stand from the hop of an arrival to before that of the next; every one goes by its own row.
    by = Window.partitionBy("id").orderBy("hop")
    kept = arrivals.select("id", "hop", F.sum("n").over(by).alias("n"), F.coalesce(F.lead("hop").over(by) - 1, F.lit(got["last"])).alias("until"))
    kept = kept.select("id", F.explode(F.sequence("hop", "until")).alias("step"), "n")
    sends = arrivals.join(arcs, arrivals["id"] == arcs["src"]).select(F.col("hop").alias("step"), "src", "dst", F.col("n").alias("size"))
    ledger.record_all(sends, list(range(got["last"] + 1)), degrees, stored=kept)


def eccentricity(g: Graph, sources: DataFrame | None = None, batches: int = 1, **options) -> DataFrame:
    """(id, ecc): the most hops to a vertex of the component. ``batches``: so many floods one after another, where the graph is
    too large for a worker; otherwise 64 sources are a batch."""
    if not options and (held := batched.hold(g, sources, incoming=True)) is not None:
        return batched.farthest(g, held).select("id", "ecc")
    out = None
    for k in range(batches):
        part = sources if sources is not None else g.vertices
        part = part.where(F.pmod("id", F.lit(batches)) == k) if batches > 1 else part
        got = all_pairs_hops(g, part, **options).groupBy(F.col("src").alias("id")).agg(F.max("hops").alias("ecc"))
        out = got if out is None else out.unionByName(got)
    return out


def diameter(g: Graph, by_component: bool = False, **options) -> DataFrame:
    """(diameter), the largest eccentricity; or (component, diameter)."""
    if not options and (held := batched.hold(g, incoming=True)) is not None:
        far = batched.farthest(g, held)
        if not by_component:
            return far.agg(F.max("ecc").alias("diameter"))
        return far.groupBy(F.col("least").alias("component")).agg(F.max("ecc").alias("diameter"))
    pairs = all_pairs_hops(g, **options)
    if not by_component:
        return pairs.agg(F.max("hops").alias("diameter"))
    return pairs.groupBy("src").agg(F.min("dst").alias("component"), F.max("hops").alias("ecc")).groupBy("component").agg(F.max("ecc").alias("diameter"))


def neighbourhood_sketch(g: Graph, steps: int, lg: int = 12) -> DataFrame:
    """(id, hop, estimate) of how many vertices lie within so many hops, from unions of distinct-count sketches."""
    rounds = Rounds(g.spark)
    arcs, _ = rounds.cut(g.simple().arcs().select("src", "dst"))
    state, _ = rounds.cut(g.vertices.groupBy("id").agg(F.hll_sketch_agg("id", lg).alias("s")))
    out = state.select("id", F.lit(0).alias("hop"), F.hll_sketch_estimate("s").alias("estimate"))
    for hop in range(1, steps + 1):
        mail = arcs.join(state, arcs["src"] == state["id"]).select(F.col("dst").alias("id"), "s")
        state, _ = rounds.cut(mail.unionByName(state).groupBy("id").agg(F.hll_union_agg("s").alias("s")))
        out = out.unionByName(state.select("id", F.lit(hop).alias("hop"), F.hll_sketch_estimate("s").alias("estimate")))
    return out


def min_label(g: Graph, ledger: Ledger | None = None, arcs: DataFrame | None = None) -> DataFrame:
    """(id, component): the least id of each component, by flooding improvements only."""
    rounds = Rounds(g.spark, ledger)
    arcs = rounds.keyed((g.symmetrized().arcs() if arcs is None else arcs).select("src", "dst"), "src")
    degrees = rounds.cut(g.degrees())[0] if ledger else None
    near = arcs.groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("m"))
    state, _ = rounds.cut(g.vertices.select("id").join(near, "id", "left").select("id", F.least("id", "m").alias("component"), F.lit(True).alias("changed")))
    while True:
        step = rounds.next()
        mail = state.where("changed").join(arcs, F.col("id") == F.col("src"))
        if ledger:
            ledger.record(step - 1, mail.select("src", "dst"), degrees)
        best = mail.groupBy(F.col("dst").alias("id")).agg(F.min("component").alias("m"))
        new = state.join(best, "id", "left").select("id", F.least("component", "m").alias("component"), F.coalesce(F.col("m") < F.col("component"), F.lit(False)).alias("changed"))
        state, got = rounds.cut(new, state, changed=count_if(F.col("changed")))
        if not got["changed"]:
            if ledger:
                ledger.steps.append((ledger.algo, step, 0, 0, 0, 0))
            return state.select("id", "component")


def shortest_paths(g: Graph, sources: DataFrame, weighted: bool = True, max_dist: float | None = None, target: int | None = None, ledger: Ledger | None = None) -> DataFrame:
    """(source, id, dist, parent) from each of ``sources`` (id). Only improvements are sent on. ``target``: stop once nothing
    on the way is nearer than it; ``max_dist``: forget what is farther."""
    rounds = Rounds(g.spark, ledger)
    w = F.col("w") if weighted and g.weight else F.lit(1.0)
    arcs = g.arcs().select("src", "dst", w.cast("double").alias("w"))
    if weighted and g.weight and arcs.where("w < 0").limit(1).count():
        raise ValueError("negative weights")
    arcs = rounds.keyed(arcs, "src")
    degrees = rounds.cut(g.degrees())[0] if ledger else None
    state, _ = rounds.cut(sources.select(F.col("id").alias("source"), "id", F.lit(0.0).alias("dist"), F.lit(None).cast("long").alias("parent"), F.lit(True).alias("changed")))
    while True:
        step = rounds.next()
        mail = state.where("changed").join(arcs, F.col("id") == F.col("src"))
        if ledger:
            ledger.record(step - 1, mail.select("src", "dst"), degrees)
        best = mail.groupBy("source", F.col("dst").alias("id")).agg(F.min(F.struct((F.col("dist") + F.col("w")).alias("d"), F.col("src").alias("p"))).alias("m"))
        if max_dist is not None:
            best = best.where(F.col("m.d") <= max_dist)
        better = F.col("m").isNotNull() & (F.col("dist").isNull() | (F.col("m.d") < F.col("dist")))
        new = state.join(best, ["source", "id"], "full").select("source", "id", F.when(better, F.col("m.d")).otherwise(F.col("dist")).alias("dist"), F.when(better, F.col("m.p")).otherwise(F.col("parent")).alias("parent"), better.alias("changed"))
        at_target = F.min(F.when(F.col("id") == F.lit(target), F.col("dist")))
        state, got = rounds.cut(new, state, changed=count_if(F.col("changed")), nearest=F.min(F.when(F.col("changed"), F.col("dist"))), there=at_target)
        if not got["changed"] or (target is not None and got["there"] and got["nearest"] >= got["there"]):
            return state.drop("changed")


def reachable(g: Graph, s: int, t: int) -> bool:
    """Whether a path leads from s to t, by two floods that grow towards each other."""
    rounds = Rounds(g.spark)
    arcs, _ = rounds.cut(g.arcs().select("src", "dst").distinct())
    one = lambda v: g.spark.createDataFrame([(v,)], "id long")
    sides = [[one(s), one(s), ("src", "dst")], [one(t), one(t), ("dst", "src")]]
    while True:
        for side in sides:
            front, seen, (a, b) = side
            if sides[0][1].join(sides[1][1], "id", "left_semi").limit(1).count():
                return True
            new = front.join(arcs, front["id"] == arcs[a]).select(F.col(b).alias("id")).distinct().join(seen, "id", "left_anti")
            new, got = rounds.cut(new, n=F.count(F.lit(1)))
            if not got["n"]:
                return bool(sides[0][1].join(sides[1][1], "id", "left_semi").limit(1).count())
            side[0], side[1] = new, rounds.cut(seen.union(new))[0]
