"""Minimum spanning forests by contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..engine import Rounds
from ..model import Graph
from .trees import pointer_jump


def picks(arcs: DataFrame, tie: str) -> DataFrame:
    """(id, ptr, u, v, w): the lightest edge of every vertex; ties by the original ends, or by the smallest neighbour."""
    order = ("w", "u", "v", "dst") if tie == "edge" else ("w", "dst", "u", "v")
    best = arcs.groupBy(F.col("src").alias("id")).agg(F.min(F.struct(*order)).alias("m"))
    return best.select("id", F.col("m.dst").alias("ptr"), "m.u", "m.v", "m.w")


def super_vertices(pick: DataFrame) -> DataFrame:
    """(id, ptr) where the smaller one of two that picked each other points at itself."""
    back = pick.select(F.col("id").alias("ptr"), F.col("ptr").alias("_back"))
    mutual = (F.col("_back") == F.col("id")) & (F.col("id") < F.col("ptr"))
    return pick.join(back, "ptr").select("id", F.when(mutual, F.col("id")).otherwise(F.col("ptr")).alias("ptr"))


def contract(arcs: DataFrame, roots: DataFrame) -> DataFrame:
    """Arcs between different roots; of parallel ones the lightest. The original ends (u, v) are carried along."""
    a, b = (roots.select(F.col("id").alias(k), F.col("root").alias(f"r{k}")) for k in ("src", "dst"))
    x = arcs.join(a, "src").join(b, "dst").where("rsrc <> rdst")
    best = x.groupBy(F.col("rsrc").alias("src"), F.col("rdst").alias("dst")).agg(F.min(F.struct("w", "u", "v")).alias("m"))
    return best.select("src", "dst", "m.w", "m.u", "m.v")


def minimum_spanning_forest(g: Graph, tie: str = "edge") -> DataFrame:
    """(src, dst, w), src < dst. With ties by edge the forest is the only one that a strict order of edges has."""
    rounds = Rounds(g.spark)
    s = g.simple()
    arcs, got = rounds.cut(s.arcs().withColumns({"u": F.least("src", "dst"), "v": F.greatest("src", "dst")}), n=F.count(F.lit(1)))
    out = None
    while got["n"]:
        rounds.next()
        pick, _ = rounds.cut(picks(arcs, tie))
        part = pick.select(F.col("u").alias("src"), F.col("v").alias("dst"), "w").distinct()
        out = part if out is None else out.unionByName(part)
        roots = pointer_jump(super_vertices(pick), rounds)
        arcs, got = rounds.cut(contract(arcs, roots), arcs, n=F.count(F.lit(1)))
    return out if out is not None else arcs.select("src", "dst", "w")
