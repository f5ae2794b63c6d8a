"""Components by hooking and shortcutting a pointer forest; weak, strong and biconnected ones; spanning forests."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..cost import Ledger
from ..engine import Rounds, count_if
from ..model import Graph
from .flood import min_label


def star_flags(ptr: DataFrame) -> DataFrame:
    """(id, ptr, in_star) of a pointer forest (id, ptr): whether the tree of a vertex has no depth beyond one."""
    up = ptr.select(F.col("id").alias("ptr"), F.col("ptr").alias("grand"))
    x = ptr.join(up, "ptr")
    deep = x.where("grand <> ptr")
    bad = deep.select("id").union(deep.select("grand")).union(deep.select("ptr")).distinct().withColumn("_no", F.lit(True))
    x = x.join(bad, "id", "left")
    parent = bad.select(F.col("id").alias("ptr"), F.lit(True).alias("_pno"))
    return x.join(parent, "ptr", "left").select("id", "ptr", (F.col("_no").isNull() & F.col("_pno").isNull()).alias("in_star"))


def _hooks(ptr: DataFrame, arcs: DataFrame, stars_only: bool, conditional: bool = True) -> DataFrame:
    """(id, to, u, v): for every root with an edge of its tree (or star) to a smaller pointer, the least such pointer."""
    flags = star_flags(ptr) if stars_only else ptr.withColumn("in_star", F.lit(True))
    a = flags.where("in_star").select(F.col("id").alias("src"), F.col("ptr").alias("pu"))
    b = ptr.select(F.col("id").alias("dst"), F.col("ptr").alias("pv"))
    x = arcs.join(a, "src").join(b, "dst").where("pv < pu" if conditional else "pv <> pu")
    roots = ptr.where("id = ptr").select(F.col("id").alias("pu"))
    best = x.groupBy("pu").agg(F.min(F.struct("pv", "src", "dst")).alias("m")).join(roots, "pu", "left_semi")
    return best.select(F.col("pu").alias("id"), F.col("m.pv").alias("to"), F.col("m.src").alias("u"), F.col("m.dst").alias("v"))


def hook_shortcut(g: Graph, star_hook: bool = True, ledger: Ledger | None = None, witnesses: list | None = None) -> DataFrame:
    """(id, component). Stops when no pointer has changed in a whole round. ``witnesses`` gathers the tables (u, v) of the
    edges that hooks went along: they are a spanning forest."""
    rounds = Rounds(g.spark, ledger)
    arcs, _ = rounds.cut(g.symmetrized().arcs().select("src", "dst"))
    ptr, _ = rounds.cut(g.vertices.select("id", F.col("id").alias("ptr")))
    degrees = rounds.cut(g.degrees())[0] if ledger else None
    while True:
        step = rounds.next()
        start = ptr
        if ledger:  # pointers are asked for and sent back; hooks are proposed along edges
            asks = ptr.select(F.col("id").alias("src"), F.col("ptr").alias("dst"))
            ledger.record(step - 1, asks.union(asks.select("dst", "src")).union(arcs.select("src", "dst")), degrees)
        changed = 0
        for stars in (False, True) if star_hook else (False,):
            hooks, got = rounds.cut(_hooks(ptr, arcs, stars), n=F.count(F.lit(1)))
            if got["n"]:
                changed += got["n"]
                if witnesses is not None:
                    witnesses.append(hooks.select("u", "v"))
                ptr, _ = rounds.cut(ptr.join(hooks.select("id", "to"), "id", "left").select("id", F.coalesce("to", "ptr").alias("ptr")), None if ptr is start else ptr)
        up = ptr.select(F.col("id").alias("ptr"), F.col("ptr").alias("grand"))
        ptr, got = rounds.cut(ptr.join(up, "ptr").select("id", F.col("grand").alias("ptr"), F.col("ptr").alias("_was")), start, moved=count_if(F.col("_was") != F.col("ptr")))
        ptr = ptr.select("id", "ptr")
        if not changed and not got["moved"]:
            return ptr.select("id", F.col("ptr").alias("component"))


def weak_components(g: Graph, engine: str = "hook", **options) -> DataFrame:
    """(id, component) without regard to direction."""
    return hook_shortcut(g, **options) if engine == "hook" else min_label(g, **options)


def spanning_forest(g: Graph, method: str = "hook") -> DataFrame:
    """(src, dst), src < dst: the edges of hooks, or of the least parents of a breadth-first flood from each component's
    least vertex."""
    ends = lambda df, a, b: df.select(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst"))
    if method == "hook":
        witnesses: list[DataFrame] = []
        hook_shortcut(g, witnesses=witnesses)
        out = g.spark.createDataFrame([], "u long, v long")
        for w in witnesses:
            out = out.union(w)
        return ends(out, "u", "v")
    rounds = Rounds(g.spark)
    arcs, _ = rounds.cut(g.symmetrized().arcs().select("src", "dst"))
    roots = hook_shortcut(g).where("id = component").select("id")
    seen, _ = rounds.cut(roots.select("id", F.lit(None).cast("long").alias("parent"), F.lit(0).alias("hop")))
    front = seen
    while True:
        hop = rounds.next()
        new = front.join(arcs, front["id"] == arcs["src"]).groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("parent")).join(seen, "id", "left_anti").withColumn("hop", F.lit(hop))
        front, got = rounds.cut(new, n=F.count(F.lit(1)))
        if not got["n"]:
            return ends(seen.where("parent is not null"), "parent", "id")
        seen = seen.unionByName(front)


def strong_components(g: Graph, trim: bool = True) -> DataFrame:
    """(id, scc). Vertices without an arc in or out are alone; then the least id floods forward, and inside each of its
    colours back from the id's owner: what is reached both ways is that owner's component."""
    rounds = Rounds(g.spark)
    arcs, _ = rounds.cut(g.edges.select("src", "dst").where("src <> dst").distinct())
    alive, got = rounds.cut(g.vertices.select("id"), n=F.count(F.lit(1)))
    done = None
    while got["n"]:
        rounds.next()
        while trim:
            both = arcs.select(F.col("src").alias("id")).distinct().join(arcs.select(F.col("dst").alias("id")).distinct(), "id", "left_semi")
            alone, seen = rounds.cut(alive.join(both, "id", "left_anti"), n=F.count(F.lit(1)))
            if not seen["n"]:
                break
            part = alone.select("id", F.col("id").alias("scc"))
            done = part if done is None else done.unionByName(part)
            alive, got = rounds.cut(alive.join(alone, "id", "left_anti"), n=F.count(F.lit(1)))
            arcs, _ = rounds.cut(arcs.join(alone, arcs["src"] == alone["id"], "left_anti").join(alone, F.col("dst") == alone["id"], "left_anti"))
        if not got["n"]:
            break
        colour = min_label(Graph(alive, arcs, True), arcs=arcs)
        a, b = (colour.select(F.col("id").alias(k), F.col("component").alias(f"c{k}")) for k in ("src", "dst"))
        inside, _ = rounds.cut(arcs.join(a, "src").join(b, "dst").where("csrc = cdst").select("src", "dst"))
        front, _ = rounds.cut(colour.where("id = component").select("id", F.col("component").alias("scc")))
        hit = front
        while True:
            new = front.join(inside, front["id"] == inside["dst"]).select(F.col("src").alias("id"), "scc").distinct().join(hit, "id", "left_anti")
            front, seen = rounds.cut(new, n=F.count(F.lit(1)))
            if not seen["n"]:
                break
            hit = hit.unionByName(front)
        hit, _ = rounds.cut(hit)
        done = hit if done is None else done.unionByName(hit)
        alive, got = rounds.cut(alive.join(hit, "id", "left_anti"), n=F.count(F.lit(1)))
        arcs, _ = rounds.cut(arcs.join(hit, arcs["src"] == hit["id"], "left_anti").join(hit, F.col("dst") == hit["id"], "left_anti"))
    return done if done is not None else alive.select("id", F.col("id").alias("scc"))
