"""Exact nearest neighbours by a block matrix join of int8 tiles.

Vectors are packed in blocks. A tile is the product of a block of queries and a block of candidates, both quantised to
int8 with a scale of their own; products of such integers are exact in float32 up to 1,040 components (longer vectors
are multiplied in float64). Each approximate product comes with a bound on its error; pairs whose upper bound reaches
the k-th best lower bound are computed again in double precision, summed from the first component to the last.

Cases: a vector that is null, empty, zero or holds a null, NaN or infinity takes no part; only vectors of one length
meet; a product that overflows has an infinite score, and minus infinity if it does so both ways; rows with one id are one vector, the least of them; ties go to the smaller id; with fewer candidates than k all
are returned; empty tables give empty results.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch

BLOCK, STRIPES = 2048, 16


def usable(vec: Column) -> Column:
    fine = F.forall(vec, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    return F.coalesce(fine & F.exists(vec, lambda x: x != 0), F.lit(False))


def quantised(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """int8 values as floats, scale and sum of absolute int8 values, of each row."""
    with np.errstate(all="ignore"):  # what is too large or too small for a scale is judged by its own products
        scale = np.abs(x).max(axis=1) / 127.0
        q = np.rint(x / scale[:, None])
    odd = ~np.isfinite(q).all(axis=1)
    q[odd], scale[odd] = 0, np.inf
    return q.astype(np.float32 if x.shape[1] <= 1040 else np.float64), scale, np.abs(q).sum(axis=1)


class Block:
    def __init__(self, ids: bytes, vecs: bytes, dim: int):
        self.ids = np.frombuffer(ids, np.int64)
        self.vecs = np.frombuffer(vecs, np.float64).reshape(-1, dim)
        self.q, self.scale, self.l1 = quantised(self.vecs)


def exact(a: np.ndarray, i: np.ndarray, b: np.ndarray, j: np.ndarray, step: int = 100_000) -> np.ndarray:
    out = np.zeros(len(i))
    for k in range(0, len(i), step):
        x, y, acc = a[i[k : k + step]], b[j[k : k + step]], np.zeros(len(i[k : k + step]))
        for d in range(a.shape[1]):
            with np.errstate(all="ignore"):
                acc += x[:, d] * y[:, d]
        out[k : k + step] = np.where(np.isnan(acc), -np.inf, acc)
    return out


class Nearest:
    """The k best of each query of a block over all candidate blocks seen so far."""

    def __init__(self, queries: Block, k: int):
        self.queries, self.k = queries, k
        self.best: list[list[tuple[float, int]]] = [[] for _ in queries.ids]  # min-heaps of (score, -id)
        self.worst = np.full(len(queries.ids), -np.inf)

    def meet(self, cands: Block) -> None:
        q, k = self.queries, self.k
        own = q.ids[:, None] == cands.ids[None, :]
        with np.errstate(all="ignore"):
            both = q.scale[:, None] * cands.scale[None, :]
            near = (q.q @ cands.q.T) * both
            slip = both * (0.5 * q.l1[:, None] + 0.5 * cands.l1[None, :] + 0.25 * q.q.shape[1]) * (1 + 1e-9) + 1e-12 * np.abs(near)
            slip += q.q.shape[1] * np.finfo(float).tiny
            low, high = near - slip, near + slip
        sure = np.isfinite(low) & np.isfinite(high)  # else nothing is known of the pair before its product
        low, high = np.where(sure & ~own, low, -np.inf), np.where(sure, high, np.inf)
        floor = self.worst
        if low.shape[1] > k:
            floor = np.maximum(floor, np.partition(low, low.shape[1] - k, axis=1)[:, low.shape[1] - k])
        i, j = np.nonzero((high >= floor[:, None]) & ~own)
        score = exact(q.vecs, i, cands.vecs, j)
        for row, s, v in zip(i.tolist(), score.tolist(), cands.ids[j].tolist(), strict=True):
            heap = self.best[row]
            if len(heap) < k:
                heapq.heappush(heap, (s, -v))
            elif (s, -v) > heap[0]:
                heapq.heapreplace(heap, (s, -v))
            if len(heap) == k:
                self.worst[row] = heap[0][0]


def nearest(df: DataFrame, id_col: str, vec_col: str, is_query: Column, k: int = 20, block: int = BLOCK) -> DataFrame:
    """(query_id, rank, vec_id, score): the k largest inner products of each row that ``is_query`` marks."""
    scratch = Scratch(df.sparkSession)
    given = df.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).cast("array<double>").alias("vec"), is_query.alias("is_query"))
    rows = given.where(usable(F.col("vec")) & F.col("vec_id").isNotNull()).groupBy("vec_id").agg(F.min("vec").alias("vec"), F.max("is_query").alias("is_query"))
    rows = scratch.keep(rows.withColumn("dim", F.size("vec")))
    n, queries = rows.agg(F.count("*"), F.coalesce(F.sum(F.col("is_query").cast("int")), F.lit(0))).first()
    q_blocks, c_blocks = max(1, -(-queries // block)), max(1, -(-n // block))

    def pack(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("vec_id")
        return pd.DataFrame({"dim": pdf.dim.iloc[:1], "blk": pdf.blk.iloc[:1], "ids": [pdf.vec_id.to_numpy(np.int64).tobytes()], "vecs": [np.stack(pdf.vec.to_list()).astype(np.float64).tobytes()]})

    def packed(part: DataFrame, blocks: int) -> DataFrame:
        at = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int").alias("blk")
        return part.select("vec_id", "vec", "dim", at).groupBy("dim", "blk").applyInPandas(pack, "dim int, blk int, ids binary, vecs binary")

    asked = scratch.keep(packed(rows.where("is_query"), q_blocks)).select("dim", F.col("blk").alias("qb"), F.col("ids").alias("q_ids"), F.col("vecs").alias("q_vecs"))
    stripes = min(STRIPES, c_blocks)
    cands = packed(rows, c_blocks).withColumn("qb", F.explode(F.sequence(F.lit(0), F.lit(q_blocks - 1))))
    tiles = cands.join(asked, ["dim", "qb"]).withColumn("stripe", F.pmod("blk", F.lit(stripes)))
    tiles = tiles.repartition(max(1, min(stripes * q_blocks, 100_000)), "dim", "qb", "stripe").sortWithinPartitions("dim", "qb", "stripe", "blk")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        at, now = None, None

        def done() -> pd.DataFrame:
            tops = [sorted(((-s, -v) for s, v in heap)) for heap in now.best]
            return pd.DataFrame({"dim": at[0], "qb": at[1], "query_id": now.queries.ids, "ids": [[v for _, v in t] for t in tops], "scores": [[-s for s, _ in t] for t in tops]})

        for b in batches:
            for r in b.itertuples(index=False):
                if (key := (r.dim, r.qb, r.stripe)) != at:
                    if now is not None:
                        yield done()
                    at, now = key, Nearest(Block(r.q_ids, r.q_vecs, r.dim), k)
                now.meet(Block(r.ids, r.vecs, r.dim))
        if now is not None:
            yield done()

    tops = tiles.mapInPandas(run, "dim int, qb int, query_id long, ids array<long>, scores array<double>")

    def merge(pdf: pd.DataFrame) -> pd.DataFrame:
        out = []
        for query, part in pdf.groupby("query_id", sort=True):
            lists = [[(-s, v) for s, v in zip(ss, vs, strict=True)] for ss, vs in zip(part.scores, part.ids, strict=True)]
            out += [(query, rank, v, -s) for rank, (s, v) in enumerate(islice(heapq.merge(*lists), k), 1)]
        return pd.DataFrame(out, columns=["query_id", "rank", "vec_id", "score"])

    return tops.groupBy("dim", "qb").applyInPandas(merge, "query_id long, rank int, vec_id long, score double")
