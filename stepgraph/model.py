"""Graphs as two tables: vertices (id, label, ...) and edges (src, dst, w, elabel)."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Graph:
    """``edges`` of an undirected graph have one row per pair; ``arcs`` gives both directions."""

    vertices: DataFrame
    edges: DataFrame
    directed: bool = False
    weight: str | None = None

    @staticmethod
    def from_edges(edges: DataFrame, directed: bool = False, vertices: DataFrame | None = None) -> Graph:
        ids = edges.select(F.col("src").alias("id")).union(edges.select("dst")).distinct()
        vertices = ids if vertices is None else vertices.join(ids, "id", "full")
        return Graph(vertices, edges, directed, "w" if "w" in edges.columns else None)

    @property
    def spark(self):
        return self.edges.sparkSession

    def simple(self) -> Graph:
        """No self-loops; of parallel edges the lightest."""
        e = self.edges.where("src <> dst")
        if not self.directed:
            e = e.withColumns({"src": F.least("src", "dst"), "dst": F.greatest("src", "dst")})
        e = e.groupBy("src", "dst").agg(F.min("w").alias("w")) if self.weight else e.select("src", "dst").distinct()
        return replace(self, edges=e)

    def arcs(self, *keep: str) -> DataFrame:
        """Directed rows (src, dst, ...): both ways for an undirected graph."""
        cols = ["src", "dst", *([self.weight] if self.weight else []), *keep]
        e = self.edges.select(*cols)
        return e if self.directed else e.unionByName(e.withColumns({"src": F.col("dst"), "dst": F.col("src")}))

    def symmetrized(self) -> Graph:
        return replace(self, directed=False).simple()

    def reversed(self) -> Graph:
        return replace(self, edges=self.edges.withColumns({"src": F.col("dst"), "dst": F.col("src")}))

    def degrees(self) -> DataFrame:
        """(id, degree): in plus out if directed."""
        ends = self.edges.select(F.col("src").alias("id")).union(self.edges.select("dst"))
        return self.vertices.select("id").join(ends.groupBy("id").agg(F.count("*").alias("degree")), "id", "left").fillna(0, ["degree"])

    def subgraph(self, vertex: Column | None = None, edge: Column | None = None) -> Graph:
        v = self.vertices if vertex is None else self.vertices.where(vertex)
        e = self.edges if edge is None else self.edges.where(edge)
        if vertex is not None:
            e = e.join(v.select(F.col("id").alias("src")), "src", "left_semi").join(v.select(F.col("id").alias("dst")), "dst", "left_semi")
        return replace(self, vertices=v, edges=e)

    def relabelled(self, mapping: DataFrame) -> Graph:
        """Under (id, to): every id by its ``to``."""
        a, b = (mapping.select(F.col("id").alias(k), F.col("to").alias(f"_{k}")) for k in ("src", "dst"))
        e = self.edges.join(a, "src").join(b, "dst").withColumns({"src": F.col("_src"), "dst": F.col("_dst")}).drop("_src", "_dst")
        return replace(self, vertices=self.vertices.join(mapping, "id").withColumn("id", F.col("to")).drop("to"), edges=e)

    def validate(self) -> DataFrame:
        """(problem, n): null ids, repeated ids, ends that are no vertex. No row means none."""
        v, e = self.vertices, self.edges
        ends = e.select(F.col("src").alias("id")).union(e.select("dst"))
        out = v.where("id is null").select(F.lit("null id").alias("problem"))
        out = out.union(v.groupBy("id").count().where("count > 1").select(F.lit("repeated id")))
        out = out.union(ends.join(v, "id", "left_anti").select(F.lit("dangling end")))
        return out.groupBy("problem").agg(F.count("*").alias("n"))

    def persist_bucketed(self, table: str, buckets: int) -> Graph:
        """Arcs as a table bucketed and sorted on src, which rounds then join without moving it."""
        self.arcs().write.bucketBy(buckets, "src").sortBy("src").mode("overwrite").saveAsTable(table)
        return replace(self, edges=self.spark.table(table), directed=True)
