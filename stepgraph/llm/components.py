"""Connected components of a table of links, by alternating star contractions on DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch


#: Up to so many links, what is joined with them is broadcast.
BROADCAST_LINKS = 500_000
LINKS_PER_TASK = 50_000


def _large(edges: DataFrame, hint) -> DataFrame:
    """Every node hangs its larger neighbours on the least node near it."""
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    return both.where("b > a").join(hint(least), "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b")


def _small(edges: DataFrame, hint) -> DataFrame:
    """Every node hangs its smaller neighbours, and itself, on the least of them."""
    least = edges.groupBy("a").agg(F.min("b").alias("m"))
    hung = edges.join(hint(least), "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return hung.unionByName(least.select("a", F.col("m").alias("b"))).distinct()


def components(links: DataFrame, scratch: Scratch, max_rounds: int = 60) -> DataFrame:
    """(node, component): the nodes of (a, b), each with the least node it reaches. Nodes may be of any ordered type."""
    n = links.count()
    hint = F.broadcast if n <= BROADCAST_LINKS else (lambda df: df)
    tasks = n // LINKS_PER_TASK + 4
    edges = links.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    for _ in range(max_rounds):
        new = scratch.keep(_small(_large(edges, hint), hint).coalesce(tasks))
        scratch.drop(edges)
        edges = new
        # Done once every node that isn't a root hangs on exactly one, and that is a root.
        roots = edges.select(F.col("b").alias("a")).distinct().withColumn("root", F.lit(1))
        if not edges.join(hint(roots), "a", "left").groupBy("a").agg(F.count("*").alias("n"), F.max("root").alias("root")).where("n > 1 or root = 1").limit(1).count():
            break
    else:
        raise RuntimeError("components have not settled")
    return edges.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(edges.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
