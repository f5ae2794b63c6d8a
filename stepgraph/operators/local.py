"""Small components are finished in one task each, many at once; only large ones take distributed rounds."""

from __future__ import annotations

from collections import deque
from collections.abc import Iterator
from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..engine import Rounds
from ..model import Graph
from . import flood
from .components import hook_shortcut

#: Edges of a component that one task takes, by default. Its floods are at most this times its vertices, in memory its arcs.
LIMIT = 2_000


def _eccentricities(edges: pd.DataFrame) -> Iterator[tuple[int, int]]:
    near: dict[int, list[int]] = {}
    for a, b in zip(edges["src"].tolist(), edges["dst"].tolist(), strict=True):
        near.setdefault(a, []).append(b)
        near.setdefault(b, []).append(a)
    for start in near:
        seen, todo, far = {start: 0}, deque([start]), 0
        while todo:
            u = todo.popleft()
            far = seen[u]
            for v in near[u]:
                if v not in seen:
                    seen[v] = far + 1
                    todo.append(v)
        yield start, far


def eccentricity(g: Graph, limit: int = LIMIT) -> DataFrame:
    """(id, ecc) of an undirected graph, the same as by floods: components of at most ``limit`` edges are flooded within one task,
    so long chains cost no round a hop; the rest goes by rounds. Vertices without edges have 0."""
    if g.directed:
        raise ValueError("components are of undirected graphs")
    rounds, simple = Rounds(g.spark), g.simple()
    edges, _ = rounds.cut(simple.edges.select("src", "dst"))
    of = hook_shortcut(Graph(g.vertices.select("id"), edges))
    owned, _ = rounds.cut(edges.join(of.select(F.col("id").alias("src"), "component"), "src"))
    sizes, got = rounds.cut(owned.groupBy("component").agg(F.count("*").alias("n")), large=F.count_if(F.col("n") > limit))
    tagged = owned.join(sizes, "component")
    solve = lambda part: pd.DataFrame(_eccentricities(part), columns=["id", "ecc"])
    out = tagged.where(F.col("n") <= limit).groupBy("component").applyInPandas(solve, "id long, ecc int")
    if got["large"]:
        big = Graph.from_edges(tagged.where(F.col("n") > limit).select("src", "dst"))
        out = out.unionByName(flood.eccentricity(replace(big, weight=None)))
    alone = g.vertices.select("id").distinct().join(edges.select(F.explode(F.array("src", "dst")).alias("id")), "id", "left_anti")
    return out.unionByName(alone.select("id", F.lit(0).alias("ecc")))
