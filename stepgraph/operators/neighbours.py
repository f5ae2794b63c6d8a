"""Nearest-neighbour graphs of vectors."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

DIGITS = 9


def knn_edges(vectors: DataFrame, k: int = 5, block_rows: int = 4096) -> DataFrame:
    """(src, dst, w), src < dst: every (id, vec) with its ``k`` nearest by cosine, to 9 digits, ties to the smaller id; w is one
    minus the cosine. A pair of blocks of about ``block_rows`` vectors is a task's work; from each only a query's k best go on.
    Vectors that are null, of no length, or hold a null or a value that isn't finite take no part."""
    fit = F.col("vec").isNotNull() & (F.size("vec") > 0) & F.forall("vec", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("vec", lambda x: x != 0)
    v = vectors.where(fit).select(F.col("id").cast("long").alias("id"), F.col("vec").cast("array<double>").alias("vec"))
    blocks = max(1, -(-v.count() // block_rows))
    v = v.withColumn("mine", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int"))
    # A block is a candidate for every block of queries: the rows sent are n times the number of blocks, and no pair is.
    cand = v.withColumn("asks", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    asks = v.withColumnRenamed("mine", "asks").withColumn("mine", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))

    def unit(frame: pd.DataFrame) -> np.ndarray:
        m = np.stack(frame.vec.to_numpy())
        m = m / np.abs(m).max(axis=1, keepdims=True)
        return m / np.linalg.norm(m, axis=1, keepdims=True)

    def best(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if a.empty or b.empty:
            return pd.DataFrame({"q": [], "c": [], "cosine": []}).astype({"q": "int64", "c": "int64", "cosine": "float64"})
        b = b.sort_values("id")
        qs, cs, right = a.id.to_numpy(), b.id.to_numpy(), unit(b).T
        left, out = unit(a), []
        for at in range(0, len(qs), 512):
            near = np.round(left[at : at + 512] @ right, DIGITS)
            near[qs[at : at + 512, None] == cs[None, :]] = -np.inf
            # candidates stand by id, so a stable sort puts the smaller id first among equals
            top = np.argsort(-near, axis=1, kind="stable")[:, :k]
            out.append(pd.DataFrame({"q": np.repeat(qs[at : at + 512], top.shape[1]), "c": cs[top].ravel(), "cosine": np.take_along_axis(near, top, 1).ravel()}))
        got = pd.concat(out)
        return got[np.isfinite(got.cosine)]

    pairs = asks.groupBy("asks", "mine").cogroup(cand.groupBy("asks", "mine")).applyInPandas(best, "q long, c long, cosine double")
    top = pairs.groupBy("q").agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("cosine")).alias("far"), "c"))), 1, k).alias("near"))
    one = top.select("q", F.explode("near").alias("n")).select(F.least("q", "n.c").alias("src"), F.greatest("q", "n.c").alias("dst"), F.round(1 + F.col("n.far"), DIGITS).alias("w"))
    return one.groupBy("src", "dst").agg(F.min("w").alias("w"))
