"""Sequential counterparts: each runs in one task on arrays and counts its elementary operations.

A graph above ``LIMIT`` edges is refused: these exist to be compared with, and to finish small rests. Methods that start anew from
each vertex share the starts out over ``SHARES`` tasks, each with the whole graph. Components take plain arrays and any size that
a worker holds.
"""

from __future__ import annotations

import heapq
from collections import defaultdict, deque
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Graph
from ..operators import batched
from ..operators.waves import Waves

LIMIT = 2_000_000
SHARES = 32
#: Rows of an answer that are handed over at once.
STEP = 100_000


class Net:
    """Adjacency of a graph and the count ``ops`` of visits, scans and heap or union steps."""

    def __init__(self, ids, edges, directed: bool):
        self.ids, self.ops, self.near, self.back = sorted(ids), 0, defaultdict(list), defaultdict(list)
        self.edges = edges
        for u, v, w in edges:
            self.near[u].append((v, w))
            self.back[v].append((u, w))
            if not directed:
                self.near[v].append((u, w))
        for k in self.near:
            self.near[k].sort()

    def bfs(self, s):
        dist, todo = {s: 0}, deque([s])
        while todo:
            u = todo.popleft()
            self.ops += 1
            for v, _ in self.near[u]:
                self.ops += 1
                if v not in dist:
                    dist[v] = dist[u] + 1
                    todo.append(v)
        return dist


def hops(net: Waves, sources):
    """Levels of each source: (source, hops, positions)."""
    for group in net.groups(sources):
        for hop, (v, nth, _, _) in enumerate(net.levels(group)):
            yield group, hop, nth, v


def components(net: Net):
    """By queue from each vertex not yet seen, in order."""
    ids = np.array(net.ids, np.int64)
    src, dst = (np.array([e[k] for e in net.edges], np.int64) for k in (0, 1))
    got = _components(ids, src, dst)
    net.ops += len(ids) + 2 * len(src)
    yield from zip(ids.tolist(), got.tolist(), strict=True)


def _components(ids: np.ndarray, src: np.ndarray, dst: np.ndarray) -> np.ndarray:
    """The least id of each one's component; ids rise. Every vertex is visited and every arc scanned once."""
    a, b = np.searchsorted(ids, np.concatenate([src, dst])), np.searchsorted(ids, np.concatenate([dst, src]))
    start = memoryview(np.concatenate([[0], np.cumsum(np.bincount(a, minlength=len(ids)))]))
    near = memoryview(b[np.argsort(a, kind="stable")])
    owner = np.full(len(ids), -1)
    of = memoryview(owner)
    for s in range(len(ids)):
        if of[s] < 0:
            of[s], todo = s, [s]
            for u in todo:
                for v in near[start[u] : start[u + 1]]:
                    if of[v] < 0:
                        of[v] = s
                        todo.append(v)
    return ids[owner]


def power_iteration(net: Net, iters: int = 10, alpha: float = 0.85):
    n, place = len(net.ids), {v: i for i, v in enumerate(net.ids)}
    degree = np.array([len(net.near[u]) for u in net.ids], np.int64)
    to = np.fromiter((place[v] for u in net.ids for v, _ in net.near[u]), np.int64)
    rank = np.full(n, 1 / n if n else 0.0)
    for _ in range(iters):
        net.ops += n + len(to)
        rank = (1 - alpha) / max(n, 1) + np.bincount(to, np.repeat(alpha * rank / np.maximum(degree, 1), degree), n)
    yield from zip(net.ids, rank.tolist(), strict=True)


def strong(net: Net):
    """One depth-first search with low links."""
    index, low, on, stack, out, n = {}, {}, set(), [], {}, 0
    for root in net.ids:
        if root in index:
            continue
        todo = [(root, iter(net.near[root]))]
        index[root] = low[root] = n
        n += 1
        stack.append(root)
        on.add(root)
        while todo:
            u, it = todo[-1]
            for v, _ in it:
                net.ops += 1
                if v not in index:
                    index[v] = low[v] = n
                    n += 1
                    stack.append(v)
                    on.add(v)
                    todo.append((v, iter(net.near[v])))
                    break
                if v in on:
                    low[u] = min(low[u], index[v])
            else:
                todo.pop()
                net.ops += 1
                if todo:
                    low[todo[-1][0]] = min(low[todo[-1][0]], low[u])
                if low[u] == index[u]:
                    group = []
                    while True:
                        w = stack.pop()
                        on.discard(w)
                        group.append(w)
                        if w == u:
                            break
                    for w in group:
                        out[w] = min(group)
    yield from out.items()


def blocks(net: Net):
    """Biconnected components by one depth-first search: (src, dst, number)."""
    index, low, n, k = {}, {}, 0, 0
    for root in net.ids:
        if root in index:
            continue
        index[root] = low[root] = n
        n += 1
        todo, edges = [(root, None, iter(net.near[root]))], []
        while todo:
            u, parent, it = todo[-1]
            for v, _ in it:
                net.ops += 1
                if v == parent:
                    continue
                if v not in index:
                    edges.append((u, v))
                    index[v] = low[v] = n
                    n += 1
                    todo.append((v, u, iter(net.near[v])))
                    break
                if index[v] < index[u]:
                    edges.append((u, v))
                    low[u] = min(low[u], index[v])
            else:
                todo.pop()
                net.ops += 1
                if parent is not None:
                    low[parent] = min(low[parent], low[u])
                    if low[u] >= index[parent]:
                        while True:
                            a, b = edges.pop()
                            yield min(a, b), max(a, b), k
                            if (a, b) == (parent, u):
                                break
                        k += 1


def tree_orders(net: Net):
    """(id, pre, post) from each component's least vertex; children in cyclic order behind the parent."""
    seen = set()
    for root in net.ids:
        if root in seen:
            continue
        pre = post = 0
        todo = [(root, None, None)]
        while todo:
            u, parent, it = todo.pop()
            if it is None:
                seen.add(u)
                net.ops += 1
                number, pre = pre, pre + 1
                near = [v for v, _ in net.near[u]]
                at = near.index(parent) + 1 if parent is not None else 0
                it = iter([(v, number) for v in near[at:] + near[: max(at - 1, 0)]])
                todo.append((u, parent, (number, it)))
                continue
            number, rest = it
            nxt = next(rest, None)
            net.ops += 1
            if nxt is None:
                post += 1
                yield u, number, post
            else:
                todo.append((u, parent, it))
                todo.append((nxt[0], u, None))


def tree_tour(net: Net):
    """Each arc and the one behind it, by walking every tree depth first from its least vertex."""
    seen = set()
    for root in net.ids:
        if root in seen or not net.near[root]:
            continue
        seen.add(root)
        walk, todo = [], [(root, None, iter([v for v, _ in net.near[root]]))]
        while todo:
            u, parent, rest = todo[-1]
            v = next(rest, None)
            net.ops += 1
            if v is None:
                todo.pop()
                if parent is not None:
                    walk.append((u, parent))
                continue
            seen.add(v)
            walk.append((u, v))
            near = [x for x, _ in net.near[v]]
            at = near.index(u)
            todo.append((v, u, iter(near[at + 1 :] + near[:at])))
        for one, behind in zip(walk, walk[1:] + walk[:1], strict=True):
            yield *one, *behind


def breadth_tree(net: Net):
    """Every vertex but the roots with its least neighbour of the level above."""
    seen = set()
    for root in net.ids:
        if root not in seen:
            dist = net.bfs(root)
            seen.update(dist)
            for v, d in dist.items():
                if d:
                    net.ops += len(net.near[v])
                    up = min(u for u, _ in net.near[v] if dist[u] == d - 1)
                    yield min(up, v), max(up, v)


class Union:
    def __init__(self, net: Net):
        self.net, self.up = net, {v: v for v in net.ids}

    def find(self, v):
        while self.up[v] != v:
            self.net.ops += 1
            self.up[v] = self.up[self.up[v]]
            v = self.up[v]
        return v


def sorted_union(net: Net):
    u = Union(net)
    for w, a, b in sorted((w, min(a, b), max(a, b)) for a, b, w in net.edges):
        net.ops += 1
        x, y = u.find(a), u.find(b)
        if x != y:
            u.up[max(x, y)] = min(x, y)
            yield a, b, w


def heap_forest(net: Net):
    seen = set()
    for s in net.ids:
        if s in seen:
            continue
        seen.add(s)
        heap = [(w, min(s, v), max(s, v), v) for v, w in net.near[s]]
        heapq.heapify(heap)
        while heap:
            w, a, b, v = heapq.heappop(heap)
            net.ops += 1
            if v in seen:
                continue
            seen.add(v)
            yield a, b, w
            for x, wx in net.near[v]:
                net.ops += 1
                if x not in seen:
                    heapq.heappush(heap, (wx, min(v, x), max(v, x), x))


def lexicographic_colours(net: Net):
    colour, left, k = {}, list(net.ids), 0
    while left:
        taken, rest = set(), []
        for v in left:
            net.ops += 1 + len(net.near[v])
            if any(u in taken for u, _ in net.near[v]):
                rest.append(v)
            else:
                taken.add(v)
                colour[v] = k
        left, k = rest, k + 1
    yield from colour.items()


def greedy_weight_matching(net: Net):
    taken = set()
    for w, a, b in sorted((-w, min(a, b), max(a, b)) for a, b, w in net.edges):
        net.ops += 1
        if a not in taken and b not in taken:
            taken |= {a, b}
            yield a, b, -w


def greedy_bipartite(net: Net):
    taken = set()
    for u in sorted({u for u, _, _ in net.edges}):
        net.ops += 1
        for v, _ in net.near[u]:
            net.ops += 1
            if v not in taken:
                taken.add(v)
                yield u, v
                break


def dependency_accumulation(net: Waves, sources):
    """What each vertex is owed, half of it as both ends of a path are sources."""
    n = len(net.degree)
    ones, score = np.ones(n), np.zeros(n)
    for group in net.groups(sources):
        net.dependencies(group, ones, ones, score)
    return score / 2


def heap_paths(net: Net):
    s = net.ids[0]
    dist, heap = {}, [(0.0, s)]
    while heap:
        d, u = heapq.heappop(heap)
        net.ops += 1
        if u in dist:
            continue
        dist[u] = d
        for v, w in net.near[u]:
            net.ops += 1
            if v not in dist:
                heapq.heappush(heap, (d + w, v))
    yield from dist.items()


def counted_simulation(net: Net, labels: dict, q_labels: dict, q_edges: list, dual: bool = False):
    """Fixpoint with a counter for every (query edge, vertex); a pair whose counter falls to none goes."""
    match = {q: {v for v, x in labels.items() if x == lab} for q, lab in q_labels.items()}
    counts, todo = {}, deque()
    tests = [(a, b, net.near, net.back) for a, b in q_edges] + ([(b, a, net.back, net.near) for a, b in q_edges] if dual else [])
    for k, (a, b, near, _) in enumerate(tests):
        for v in list(match[a]):
            counts[k, v] = sum(1 for u, _ in near[v] if u in match[b])
            net.ops += 1 + len(near[v])
    for k, (a, _, _, _) in enumerate(tests):
        todo += [(a, v) for v in match[a] if counts[k, v] == 0]
    while todo:
        q, v = todo.popleft()
        if v not in match[q]:
            continue
        match[q].discard(v)
        for k, (a, b, _, back) in enumerate(tests):
            if b == q:
                for u, _ in back[v]:
                    net.ops += 1
                    if u in match[a] and (k, u) in counts:
                        counts[k, u] -= 1
                        if counts[k, u] == 0:
                            todo.append((a, u))
    if all(match.values()):
        for q, vs in match.items():
            for v in vs:
                yield q, v


def strong_balls(net: Net, labels: dict, q_labels: dict, q_edges: list, radius: int):
    """Dual simulation in the ball round every vertex, cut to the piece that realised query edges connect with the centre."""
    for centre in net.ids:
        ball, front = {centre}, {centre}
        for _ in range(radius):
            front = {v for u in front for v, _ in net.near[u] + net.back[u]} - ball
            ball |= front
        part = Net(ball, [(u, v, w) for u in ball for v, w in net.near[u] if v in ball], True)
        match = list(counted_simulation(part, {v: labels.get(v) for v in ball}, q_labels, q_edges, True))
        net.ops += part.ops + len(ball)
        roles = defaultdict(set)
        for q, v in match:
            roles[v].add(q)
        if centre not in roles:
            continue
        real = defaultdict(list)
        for u in roles:
            for v, _ in part.near[u]:
                net.ops += 1
                if any(a in roles[u] and b in roles.get(v, ()) for a, b in q_edges):
                    real[u].append(v)
                    real[v].append(u)
        hit, todo = {centre}, [centre]
        while todo:
            for v in real[todo.pop()]:
                if v not in hit:
                    hit.add(v)
                    todo.append(v)
        for q, v in match:
            if v in hit:
                yield centre, q, v


ANSWERS = {
    hops: "src long, dst long, hops long", components: "id long, component long", power_iteration: "id long, rank double", strong: "id long, scc long", blocks: "src long, dst long, block long",
    tree_orders: "id long, pre long, post long", sorted_union: "src long, dst long, w double", heap_forest: "src long, dst long, w double", lexicographic_colours: "id long, color int",
    greedy_weight_matching: "src long, dst long, w double", greedy_bipartite: "left long, right long", dependency_accumulation: "id long, score double", heap_paths: "id long, dist double", counted_simulation: "q int, id long",
    tree_tour: "src long, dst long, next_src long, next_dst long", breadth_tree: "src long, dst long", strong_balls: "center long, q int, id long",
}


def _shared_out(g: Graph, method: Callable) -> DataFrame:
    """The method on shares of the sources, each in a task with the whole graph: (src, far, hops) or (id, score), each row with
    its share and the operations of this up to that row. A row of hops has all vertices ``far`` that are so many hops away."""
    held = batched.hold(g)
    if held is None or len(held.ids) + len(held.near) // (1 if g.directed else 2) > LIMIT:
        raise ValueError(f"more than {LIMIT} rows, or null ids: a sequential baseline is for small graphs")
    spark, shares, step = g.spark, SHARES, STEP
    sent = spark.sparkContext.broadcast(held)

    def blocks(rows: Iterator[tuple], ids: np.ndarray) -> Iterator[list]:
        """Rows of lists, ``step`` vertices or more at once."""
        src, hops, far, many, n = [], [], [], [], 0
        for group, hop, nth, v in rows:
            if n >= step:
                yield [src, hops, far, many]
                src, hops, far, many, n = [], [], [], [], 0
            sizes = np.bincount(nth, minlength=len(group))
            hit = np.flatnonzero(sizes)
            src.append(ids[group[hit]])
            hops.append(np.full(len(hit), hop))
            far.append(ids.take(v))
            many.append(sizes[hit])
            n += len(v)
        if n:
            yield [src, hops, far, many]

    def levels(numbers: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = sent.value
        for k in (k for b in numbers for k in b.column("id").to_pylist()):
            net = Waves(held.start, held.near, held.low, held.high)
            for block in blocks(hops(net, held.sources[k::shares]), held.ids):
                src, hop, far, many = (np.concatenate(x) for x in block)
                lists = pa.ListArray.from_arrays(np.concatenate([[0], np.cumsum(many)]).astype(np.int32), pa.array(far))
                same = [pa.array(np.full(len(src), x)) for x in (k, net.ops)]
                yield pa.RecordBatch.from_arrays([pa.array(src), lists, pa.array(hop), *same], ["src", "far", "hops", "share", "ops"])

    def scores(numbers: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = sent.value
        for k in (k for b in numbers for k in b.column("id").to_pylist()):
            net = Waves(held.start, held.near, held.low, held.high)
            got = dependency_accumulation(net, held.sources[k::shares])[held.sources]
            same = [pa.array(np.full(len(got), x)) for x in (k, net.ops)]
            yield pa.RecordBatch.from_arrays([pa.array(held.ids[held.sources]), pa.array(got), *same], ["id", "score", "share", "ops"])

    numbers = spark.range(0, shares, 1, shares)
    if method is hops:
        return numbers.mapInArrow(levels, "src long, far array<long>, hops long, share long, ops long")
    return numbers.mapInArrow(scores, "id long, score double, share long, ops long")


def _whole_components(rows: DataFrame, kind: str) -> DataFrame:
    """The same as ``components``, from and to Arrow arrays in one task."""
    step = STEP

    def one(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        if not held:
            return
        table = pa.Table.from_batches(held)
        edge = table.filter(pc.is_valid(table.column("b")))
        src, dst = (edge.column(c).to_numpy() for c in "ab")
        ids = np.unique(table.column("a").to_numpy())
        got = _components(ids, src, dst)
        ops = len(ids) + 2 * len(src)
        for i in range(0, len(ids), step):
            part = ids[i : i + step]
            yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(got[i : i + step]), pa.array(np.full(len(part), ops))], ["id", "component", "ops"])

    return rows.select("a", "b").repartition(1).mapInArrow(one, f"{kind}, ops long")


def run(g: Graph, method: Callable, **args) -> DataFrame:
    """The method's answer with one more column, ops, which is the same in every row."""
    kind = ANSWERS[method]
    cols = [c.split()[0] for c in kind.split(", ")]
    directed, limit = g.directed, LIMIT
    w = F.col("w").cast("double") if g.weight else F.lit(1.0)
    e = g.simple().edges.select(F.col("src").alias("a"), F.col("dst").alias("b"), w.alias("w"), F.lit(None).cast("string").alias("label"))
    label = F.col("label") if "label" in g.vertices.columns else F.lit(None).cast("string")
    v = g.vertices.select(F.col("id").alias("a"), F.lit(None).cast("long").alias("b"), F.lit(None).cast("double").alias("w"), label.alias("label"))

    if method in (hops, dependency_accumulation):
        out = _shared_out(g, method)
        if method is hops:
            return out.select("src", F.explode("far").alias("dst"), "hops", "share", "ops")
        return out.groupBy("id").agg(F.sum("score").alias("score"), F.sum("ops").alias("ops"))
    if method is components and not directed:
        return _whole_components(e.unionByName(v), kind)

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        if len(pdf) > limit:
            raise ValueError(f"more than {limit} rows: a sequential baseline is for small graphs")
        edge = pdf[pdf.b.notna()]
        net = Net(set(pdf.a[pdf.b.isna()].tolist()), list(zip(edge.a.tolist(), edge.b.astype("int64").tolist(), edge.w.tolist(), strict=True)), directed)
        more = dict(args)
        if method in (counted_simulation, strong_balls):
            more["labels"] = dict(zip(pdf.a[pdf.b.isna()].tolist(), pdf.label[pdf.b.isna()].tolist(), strict=True))
        out = pd.DataFrame(list(method(net, **more)), columns=cols)
        return out.assign(ops=net.ops)

    return e.unionByName(v).groupBy(F.lit(0).alias("one")).applyInPandas(one, f"{kind}, ops long")


def operations(g: Graph, method: Callable, **args) -> int:
    """The method's elementary operations on the graph."""
    if method is hops:  # a share's count grows over its rows; these need not be told apart by vertex to be counted
        return _shared_out(g, method).groupBy("share").agg(F.max("ops").alias("ops")).agg(F.sum("ops")).first()[0]
    return run(g, method, **args).agg(F.max("ops")).first()[0]
