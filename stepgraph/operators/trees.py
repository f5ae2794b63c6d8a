"""Trees: Euler tours, list ranking, orders, depth and size; pointer jumping; biconnected components."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..cost import Ledger
from ..engine import Rounds, count_if
from ..model import Graph
from .components import hook_shortcut, spanning_forest


def euler_tour(tree: Graph, ledger: Ledger | None = None) -> DataFrame:
    """(src, dst, next_src, next_dst): behind (u, v) comes (v, w), w being v's neighbour after u in cyclic order."""
    arcs = tree.symmetrized().arcs().select("src", "dst")
    w = Window.partitionBy("src").orderBy("dst")
    after = F.coalesce(F.lead("dst").over(w), F.first("dst").over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
    if ledger:
        ledger.record(0, arcs, tree.degrees(), stored=tree.degrees().withColumnRenamed("degree", "n"))
        ledger.record(1, arcs.limit(0), active=tree.vertices)
    return arcs.withColumn("next", after).select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("src").alias("next_src"), F.col("next").alias("next_dst"))


def list_rank(items: DataFrame, values: tuple[str, ...] = ("val",), ledger: Ledger | None = None) -> DataFrame:
    """Adds sum_<value>, the sum from the head on, to (id, pred, ...): pointers double until all stand at their head."""
    rounds = Rounds(items.sparkSession, ledger)
    sums = [f"sum_{v}" for v in values]
    state, _ = rounds.cut(items.select("id", "pred", *[F.col(v).alias(s) for v, s in zip(values, sums, strict=True)]))
    while True:
        # Those that have reached their head only answer; each answers one asker at most.
        step = rounds.next()
        if ledger:
            ledger.record(step - 1, state.where("pred is not null").select(F.col("id").alias("src"), F.col("pred").alias("dst")))
        other = state.select(F.col("id").alias("pred"), F.col("pred").alias("_pp"), *[F.col(s).alias(f"_{s}") for s in sums])
        new = state.join(other, "pred", "left").select("id", F.col("_pp").alias("pred"), *[(F.col(s) + F.coalesce(f"_{s}", F.lit(0))).alias(s) for s in sums])
        state, got = rounds.cut(new, state, open=count_if(F.col("pred").isNotNull()))
        if not got["open"]:
            break
    return items.join(state.select("id", *sums), "id")


def pointer_jump(ptr: DataFrame, rounds: Rounds | None = None) -> DataFrame:
    """(id, root) of (id, ptr), whose roots point at themselves."""
    rounds = rounds or Rounds(ptr.sparkSession)
    state, _ = rounds.cut(ptr.select("id", "ptr"))
    while True:
        rounds.next()
        up = state.select(F.col("id").alias("ptr"), F.col("ptr").alias("_up"))
        new = state.join(up, "ptr").select("id", F.col("_up").alias("ptr"), (F.col("_up") != F.col("ptr")).alias("_moved"))
        new, got = rounds.cut(new, state, moved=count_if(F.col("_moved")))
        state = new.drop("_moved")
        if not got["moved"]:
            return state.select("id", F.col("ptr").alias("root"))


def mark_direction(ranked: DataFrame) -> DataFrame:
    """Adds forward to (src, dst, sum): an edge is forward if it stands before its mirror in the tour."""
    mirror = ranked.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("sum").alias("_m"))
    return ranked.join(mirror, ["src", "dst"]).withColumn("forward", F.col("sum") < F.col("_m")).drop("_m")


def tree_orders(forest: Graph, roots: DataFrame | None = None) -> DataFrame:
    """(id, root, parent, pre, post, depth, size) of trees; ``roots`` (id): one a tree, by default its least vertex.

    The root is 0 in pre-order and n in post-order. Children follow in ascending order, cyclically from the parent's place.
    """
    rounds = Rounds(forest.spark)
    if roots is None:
        comp, _ = rounds.cut(hook_shortcut(forest))
        roots = comp.where("id = component").select("id")
    tour = euler_tour(forest)
    key = lambda a, b: F.struct(F.col(a).alias("a"), F.col(b).alias("b"))
    first = forest.symmetrized().arcs().groupBy(F.col("src").alias("id")).agg(F.min("dst").alias("d")).join(roots, "id").select(key("id", "d").alias("id"))
    items = tour.select(key("next_src", "next_dst").alias("id"), key("src", "dst").alias("pred"))
    items = items.join(first.withColumn("_head", F.lit(True)), "id", "left").select("id", F.when(F.col("_head").isNull(), F.col("pred")).alias("pred"))
    items, _ = rounds.cut(items.withColumn("one", F.lit(1).cast("long")))
    ranked = list_rank(items, ("one",)).select("id.a", "id.b", F.col("sum_one").alias("sum"))
    marked = mark_direction(ranked.select(F.col("a").alias("src"), F.col("b").alias("dst"), "sum"))
    marked, _ = rounds.cut(marked.select(key("src", "dst").alias("id"), "forward", "sum"))
    steps = marked.join(items.select("id", "pred"), "id").select("id", "pred", "forward", "sum", F.col("forward").cast("long").alias("down"), (~F.col("forward")).cast("long").alias("up"))
    steps, _ = rounds.cut(list_rank(steps, ("down", "up")))
    down = steps.where("forward").select(F.col("id.a").alias("parent"), F.col("id.b").alias("id"), F.col("sum_down").alias("pre"), (F.col("sum_down") - F.col("sum_up")).alias("depth"), F.col("sum").alias("_in"))
    up = steps.where("not forward").select(F.col("id.a").alias("id"), F.col("sum_up").alias("post"), F.col("sum").alias("_out"))
    inner = down.join(up, "id").withColumn("size", ((F.col("_out") - F.col("_in") + 1) / 2).cast("long")).drop("_in", "_out")
    rooted, _ = rounds.cut(hook_shortcut(forest))
    named = roots.join(rooted, "id").select(F.col("id").alias("root"), "component")
    sizes = rooted.groupBy("component").agg(F.count("*").alias("n"))
    top = named.join(sizes, "component").select(F.col("root").alias("id"), "root", F.lit(None).cast("long").alias("parent"), F.lit(0).cast("long").alias("pre"), F.col("n").alias("post"), F.lit(0).cast("long").alias("depth"), F.col("n").alias("size"))
    rest = inner.join(rooted, "id").join(named, "component").select("id", "root", "parent", "pre", "post", "depth", "size")
    return top.unionByName(rest)


def biconnected(g: Graph) -> DataFrame:
    """(src, dst, block): src < dst; a block is named by the least tree child (in order) of its edges.

    Pre-order and subtree sizes of any spanning forest; the least and largest pre-order that a subtree's other edges reach;
    tree edges that must share a block are linked, and the links' components are the blocks.
    """
    rounds = Rounds(g.spark)
    edges, _ = rounds.cut(g.symmetrized().edges.select("src", "dst"))
    forest, _ = rounds.cut(spanning_forest(g))
    info, _ = rounds.cut(tree_orders(Graph(g.vertices.select("id"), forest)))
    # one numbering for all trees: pre-orders of a tree follow those of the trees before it
    sizes = info.where("parent is null").select("root", "size")
    offset = sizes.withColumn("off", F.coalesce(F.sum("size").over(Window.orderBy("root").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("root", "off")
    info, _ = rounds.cut(info.join(offset, "root").withColumn("pre", F.col("pre") + F.col("off")).drop("off"))
    other, _ = rounds.cut(edges.join(forest, ["src", "dst"], "left_anti"))
    p = info.select("id", "pre")
    a, b = (p.select(F.col("id").alias(k), F.col("pre").alias(f"p{k}")) for k in ("src", "dst"))
    cross, _ = rounds.cut(other.join(a, "src").join(b, "dst"))
    reach = cross.select(F.col("src").alias("id"), F.col("pdst").alias("p")).union(cross.select("dst", "psrc")).union(p)
    state, _ = rounds.cut(reach.groupBy("id").agg(F.min("p").alias("low"), F.max("p").alias("high")).join(info.select("id", "parent", "depth"), "id"))
    top = state.agg(F.max("depth")).first()[0] or 0
    for depth in range(top, 0, -1):  # subtree minimum and maximum, from the deepest level up
        from_below = state.where(F.col("depth") == depth).groupBy(F.col("parent").alias("id")).agg(F.min("low").alias("l"), F.max("high").alias("h"))
        state, _ = rounds.cut(state.join(from_below, "id", "left").select("id", F.least("low", "l").alias("low"), F.greatest("high", "h").alias("high"), "parent", "depth"), state)
    x, _ = rounds.cut(info.join(state.select("id", "low", "high"), "id"))
    v = x.select(F.col("id").alias("parent"), F.col("pre").alias("vp"), F.col("size").alias("vs"), F.col("parent").alias("vv"))
    down = x.where("parent is not null").join(v, "parent").where("vv is not null and (low < vp or high >= vp + vs)")
    link = down.select(F.col("parent").alias("src"), F.col("id").alias("dst"))
    s = info.select("id", "size")
    c = cross.join(s.select(F.col("id").alias("src"), F.col("size").alias("ss")), "src").join(s.select(F.col("id").alias("dst"), F.col("size").alias("sd")), "dst")
    unrelated = c.where("(psrc < pdst and psrc + ss <= pdst) or (pdst < psrc and pdst + sd <= psrc)").select("src", "dst")
    inner = x.where("parent is not null").select("id")
    blocks, _ = rounds.cut(hook_shortcut(Graph(inner, link.union(unrelated))))
    tree = x.where("parent is not null").select(F.least("id", "parent").alias("src"), F.greatest("id", "parent").alias("dst"), "id")
    later = cross.select("src", "dst", F.when(F.col("psrc") > F.col("pdst"), F.col("src")).otherwise(F.col("dst")).alias("id"))
    return tree.union(later).join(blocks, "id").select("src", "dst", F.col("component").alias("block"))


def bridges(blocks: DataFrame) -> DataFrame:
    one = blocks.groupBy("block").agg(F.count("*").alias("n"), F.first("src").alias("src"), F.first("dst").alias("dst")).where("n = 1")
    return one.select("src", "dst")


def articulation_points(blocks: DataFrame) -> DataFrame:
    ends = blocks.select(F.col("src").alias("id"), "block").union(blocks.select("dst", "block")).distinct()
    return ends.groupBy("id").count().where("count > 1").select("id")
