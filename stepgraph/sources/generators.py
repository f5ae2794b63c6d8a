"""Graphs made by a rule, for tests and for the growth of costs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.coins import draw
from ..model import Graph


def _graph(n: DataFrame, edges: DataFrame) -> Graph:
    return Graph(n, edges)


def path(spark: SparkSession, n: int) -> Graph:
    return _graph(spark.range(n), spark.range(max(0, n - 1)).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst")))


def cycle(spark: SparkSession, n: int) -> Graph:
    return _graph(spark.range(n), spark.range(n).select(F.col("id").alias("src"), ((F.col("id") + 1) % n).alias("dst")))


def star(spark: SparkSession, n: int) -> Graph:
    return _graph(spark.range(n), spark.range(1, n).select(F.lit(0).cast("long").alias("src"), F.col("id").alias("dst")))


def complete(spark: SparkSession, n: int) -> Graph:
    pairs = spark.range(n * n).select(F.floor(F.col("id") / n).cast("long").alias("src"), (F.col("id") % n).alias("dst"))
    return _graph(spark.range(n), pairs.where("src < dst"))


def grid(spark: SparkSession, a: int, b: int) -> Graph:
    cells = spark.range(a * b)
    right = cells.where((F.col("id") % b) < b - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    return _graph(cells, right.union(cells.where(F.col("id") < (a - 1) * b).select("id", F.col("id") + b)))


def random_tree(spark: SparkSession, n: int, seed: int = 1) -> Graph:
    """Each vertex hangs on a smaller one."""
    return _graph(spark.range(n), spark.range(1, n).select(F.pmod(draw(F.col("id"), seed), F.col("id")).alias("src"), F.col("id").alias("dst")))


def random_graph(spark: SparkSession, n: int, m: int, seed: int = 1, weights: bool = False) -> Graph:
    e = spark.range(m).select(F.pmod(draw(F.col("id"), seed, 1), F.lit(n)).alias("src"), F.pmod(draw(F.col("id"), seed, 2), F.lit(n)).alias("dst"), F.pmod(draw(F.col("id"), seed, 3), F.lit(1000)).cast("double").alias("w"))
    return Graph(spark.range(n), e if weights else e.select("src", "dst"), False, "w" if weights else None)
