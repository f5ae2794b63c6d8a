"""Floods from many sources over a graph that a worker can hold.

The arcs go to all workers once, as arrays, and sources are shared out over tasks; so no pair of vertices is written or moved
unless it is asked for. Vertices stand in order of component and id, and a flood looks at its sources' components only. Hop
floods go from 64 sources at a time, each a bit of one word a vertex. Graphs of more than ``ARCS`` arcs are not for this: they
take distributed rounds.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Graph
from .waves import Waves

#: Most arcs of a graph that is sent to the workers: 16 bytes each on the driver, 4 in a worker.
ARCS = 5_000_000
BITS = 64
#: Vertices whose pairs are handed over at once, up to 64 each.
STEP = 4096


@dataclass
class Held:
    """ids by position; arcs of position v: ``near[start[v]:start[v + 1]]``; ``low`` and ``high``: where its component begins and
    ends; sources: positions, rising."""

    ids: np.ndarray
    start: np.ndarray
    near: np.ndarray
    low: np.ndarray
    high: np.ndarray
    sources: np.ndarray


def _labels(n: int, src: np.ndarray, dst: np.ndarray) -> np.ndarray:
    """Least vertex of each weak component, by hooking and shortcutting."""
    label = np.arange(n)
    while True:
        a, b = label[src], label[dst]
        apart = a != b
        if not apart.any():
            return label
        np.minimum.at(label, np.maximum(a, b)[apart], np.minimum(a, b)[apart])
        while ((up := label[label]) != label).any():
            label = up


def hold(g: Graph, sources: DataFrame | None = None, incoming: bool = False) -> Held | None:
    """The graph with its arcs out of (or into) each vertex, or None where it is too large or has null ids."""
    arcs = g.simple().arcs().select("src", "dst").limit(ARCS + 1).toArrow()
    if arcs.num_rows > ARCS:
        return None
    ends = [arcs.column(k) for k in ("src", "dst")]
    own = g.vertices.select(F.col("id").cast("long")).distinct().limit(ARCS + 1).toArrow().column("id")
    picked = own if sources is None else sources.select(F.col("id").cast("long")).distinct().toArrow().column("id")
    if len(own) > ARCS or any(c.null_count for c in (*ends, own, picked)):
        return None
    src, dst = (c.to_numpy().astype(np.int64) for c in ends)
    own, picked = own.to_numpy(), picked.to_numpy()
    ids = np.unique(np.concatenate([own, src, dst, picked]))
    src, dst = np.searchsorted(ids, src), np.searchsorted(ids, dst)
    label = _labels(len(ids), src, dst)
    order = np.argsort(label, kind="stable")
    place = np.empty(len(ids), np.int64)
    place[order] = np.arange(len(ids))
    begins, which, sizes = np.unique(label[order], return_inverse=True, return_counts=True)
    low = (np.cumsum(sizes) - sizes)[which]
    a, b = (place[dst], place[src]) if incoming else (place[src], place[dst])
    start = np.concatenate([[0], np.cumsum(np.bincount(a, minlength=len(ids)))])
    at = np.sort(place[np.searchsorted(ids, picked)])
    return Held(ids[order], start, b[np.lexsort((b, a))].astype(np.int32), low, low + sizes[which], at)


def _shared_out(g: Graph, held: Held, run, kind: str, least: int = 0) -> DataFrame:
    """``run(held, batches)`` in tasks, over the numbers of batches of 64 sources, ``least`` at least."""
    spark, batches = g.spark, max(least, -(-len(held.sources) // BITS))
    sent = spark.sparkContext.broadcast(held)
    tasks = max(1, min(batches, 4 * spark.sparkContext.defaultParallelism))

    def part(numbers: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(sent.value, (k for b in numbers for k in b.column("id").to_pylist()))

    return spark.range(0, batches, 1, tasks).mapInArrow(part, kind)


def _floods(held: Held, k: int, most: int | None = None) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(hop, a, new, sources): bit j of ``new[v - a]`` says that v is reached from source j in that hop, and not before."""
    src = held.sources[BITS * k : BITS * (k + 1)]
    a, b = int(held.low[src[0]]), int(held.high[src[-1]])
    new = np.zeros(b - a, np.uint64)
    new[src - a] = np.uint64(1) << np.arange(len(src), dtype=np.uint64)
    seen, hop = new.copy(), 0
    s = held.start[a : b + 1]
    near, heads = held.near[s[0] : s[-1]] - a, np.flatnonzero(np.diff(s))
    offs = s[heads] - s[0]
    yield hop, a, new, src
    while len(heads) and (most is None or hop < most):
        got = np.zeros(b - a, np.uint64)
        got[heads] = np.bitwise_or.reduceat(new[near], offs)
        new = got & ~seen
        if not new.any():
            return
        seen |= new
        hop += 1
        yield hop, a, new, src


def _bits(words: np.ndarray, n: int) -> np.ndarray:
    return np.unpackbits(words.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")[:, :n]


def pairs(g: Graph, held: Held, max_hops: int | None = None) -> DataFrame:
    """(src, dst, hops)"""

    def run(held: Held, batches: Iterator[int]) -> Iterator[pa.RecordBatch]:
        for k in batches:
            for hop, a, new, src in _floods(held, k, max_hops):
                hit = np.flatnonzero(new)
                for i in range(0, len(hit), STEP):
                    at = hit[i : i + STEP]
                    v, j = np.nonzero(_bits(new[at], len(src)))
                    columns = held.ids[src[j]], held.ids[a + at[v]], np.full(len(v), hop, np.int32)
                    yield pa.RecordBatch.from_arrays([*map(pa.array, columns)], ["src", "dst", "hops"])

    return _shared_out(g, held, run, "src long, dst long, hops int")


def farthest(g: Graph, held: Held) -> DataFrame:
    """(id, ecc, least) of the sources: the most hops to what they reach, and the least id of that."""
    directed = g.directed

    def run(held: Held, batches: Iterator[int]) -> Iterator[pa.RecordBatch]:
        for k in batches:
            ecc = least = None
            for hop, a, new, src in _floods(held, k):
                if ecc is None:
                    ecc, least = np.zeros(len(src), np.int32), src.copy() if directed else held.low[src]
                ecc[_bits(np.bitwise_or.reduce(new)[None], len(src))[0] == 1] = hop
                for j in range(len(src)):
                    if least[j] > held.low[src[j]]:
                        hit = (new >> np.uint64(j)) & np.uint64(1)
                        first = int(np.argmax(hit))
                        least[j] = min(least[j], a + first) if hit[first] else least[j]
            yield pa.RecordBatch.from_arrays([pa.array(held.ids[src]), pa.array(ecc), pa.array(held.ids[least])], ["id", "ecc", "least"])

    return _shared_out(g, held, run, "id long, ecc int, least long")


def arrivals(g: Graph, held: Held, max_hops: int | None = None) -> DataFrame:
    """(id, hop, n): from how many sources a vertex is so many hops away."""

    def run(held: Held, batches: Iterator[int]) -> Iterator[pa.RecordBatch]:
        sums: list[np.ndarray] = []
        for k in batches:
            for hop, a, new, _ in _floods(held, k, max_hops):
                if hop == len(sums):
                    sums.append(np.zeros(len(held.ids), np.int64))
                sums[hop][a : a + len(new)] += np.bitwise_count(new)
        for hop, n in enumerate(sums):
            at = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array(held.ids[at]), pa.array(np.full(len(at), hop, np.int32)), pa.array(n[at])], ["id", "hop", "n"])

    return _shared_out(g, held, run, "id long, hop int, n long").groupBy("id", "hop").agg(F.sum("n").alias("n"))


@dataclass
class Folded(Held):
    """What is left without the trees that hang on a graph. ``reach`` and ``times``: how many vertices, and how many of the
    sources, a vertex stands for; ``whole`` and ``base``: all ids, and what each is owed of paths that a tree makes the only ones."""

    reach: np.ndarray
    times: np.ndarray
    whole: np.ndarray
    base: np.ndarray


def fold(held: Held, directed: bool = False) -> Folded:
    """Vertices with one neighbour go into it, again and again; arcs go both ways. Whatever is cut off a vertex that way lies
    apart from the rest without it, so it is on all paths from there to elsewhere, which counts give. A directed graph stays whole."""
    n = len(held.ids)
    reach, own, pairs = np.ones(n), np.zeros(n), np.zeros(n)
    own[held.sources] = 1
    times, left = own.copy(), np.ones(n, bool)
    if directed:
        return Folded(held.ids, held.start, held.near, held.low, held.high, held.sources, reach, times, held.ids, np.zeros(n))
    degree, near = np.diff(held.start), held.near.astype(np.int64)
    # The only neighbour left is the xor of all and those that have gone.
    only = np.zeros(n, np.int64)
    has = np.flatnonzero(degree)
    if len(has):
        only[has] = np.bitwise_xor.reduceat(near, held.start[has])
    leaf = np.flatnonzero(degree == 1)
    while len(leaf):
        up = only[leaf]
        go = (degree[up] > 1) | (leaf > up)  # of two that have each other only, one stays
        leaf, up = leaf[go], up[go]
        left[leaf] = False
        np.add.at(pairs, up, times[leaf] * reach[leaf])
        np.add.at(reach, up, reach[leaf])
        np.add.at(times, up, times[leaf])
        np.subtract.at(degree, up, 1)
        np.bitwise_xor.at(only, up, leaf)
        leaf = np.unique(up[degree[up] == 1])
    size = (held.high - held.low).astype(float)
    many = np.concatenate([[0.0], np.cumsum(own)])
    many = many[held.high] - many[held.low]
    base = (times - own) * (size - 1) - pairs + (many - times) * (reach - 1)
    place = np.concatenate([[0], np.cumsum(left)])
    tails = np.repeat(np.arange(n), np.diff(held.start))
    arc = left[tails] & left[near]
    at = np.flatnonzero(left)
    start = np.concatenate([[0], np.cumsum(np.bincount(place[tails[arc]], minlength=len(at)))])
    core = held.ids[at], start, place[near[arc]].astype(np.int32), place[held.low[at]], place[held.high[at]]
    picked = np.flatnonzero((times[at] > 0) & (np.diff(start) > 0))
    return Folded(*core, picked, reach[at], times[at], held.ids, base)


def dependencies(g: Graph, held: Held) -> DataFrame:
    """(id, d): sums over the sources."""

    def run(held: Folded, batches: Iterator[int]) -> Iterator[pa.RecordBatch]:
        total, waves = np.zeros(len(held.ids)), Waves(held.start, held.near, held.low, held.high)
        shares, n = max(1, -(-len(held.sources) // BITS)), len(held.whole)
        for k in batches:
            for group in waves.groups(held.sources[BITS * k : BITS * (k + 1)]):
                waves.dependencies(group, held.reach, held.times, total)
            own = slice(n * k // shares, n * (k + 1) // shares)
            yield pa.RecordBatch.from_arrays([pa.array(held.whole[own]), pa.array(held.base[own])], ["id", "d"])
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(held.ids[at]), pa.array(total[at])], ["id", "d"])

    return _shared_out(g, fold(held, g.directed), run, "id long, d double", 1).groupBy("id").agg(F.sum("d").alias("d"))
