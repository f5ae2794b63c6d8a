"""Breadth-first levels from several sources at once, on arrays, each source apart from the others.

No step looks at more than the arcs out of the level before, so a flood costs the visits and scans of a queue.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

#: Places (source, vertex) of floods that go side by side, so that their marks stay near the processor.
ROOM = 65_536


class Waves:
    """Arcs of vertex v: ``near[start[v]:start[v + 1]]``; its component: from ``low[v]`` to before ``high[v]``. ``ops`` counts
    visits and scans."""

    def __init__(self, start: np.ndarray, near: np.ndarray, low: np.ndarray, high: np.ndarray):
        self.start, self.near, self.low, self.high, self.ops = start.astype(np.int64), near.astype(np.int64), low, high, 0
        self.degree = np.diff(self.start)
        self.fresh, self.mark, self.count = np.ones(0, bool), np.zeros(0, np.int64), np.arange(0)

    def groups(self, sources: np.ndarray) -> Iterator[np.ndarray]:
        """The sources in stretches that have room side by side; one alone always has."""
        room = (self.high - self.low)[sources]
        i = 0
        while i < len(sources):
            n = max(1, int(np.searchsorted(np.cumsum(room[i : i + 1024]), ROOM, "right")))
            yield sources[i : i + n]
            i += n

    def _upto(self, n: int) -> np.ndarray:
        if n > len(self.count):
            self.count = np.arange(2 * n)
        return self.count[:n]

    def levels(self, sources: np.ndarray, links: bool = False) -> Iterator[tuple]:
        """(v, nth, tail, head) of each level: the vertices, and the place of the source that reached them, which rises. With
        ``links``: arcs from place ``tail`` of the level before to place ``head`` of this one."""
        lone = len(sources) == 1  # marked by vertex; otherwise each flood has its own stretch of marks
        room = (self.high - self.low)[sources]
        ends = np.cumsum(room)
        shift = ends - room - self.low[sources]
        most = int(self.high[sources[0]] if lone else ends[-1])
        if most > len(self.fresh):
            self.fresh, self.mark = np.ones(most, bool), np.zeros(most, np.int64)
        v, nth, tail, head, reached = sources, np.arange(len(sources)), None, None, []
        while True:
            key = v if lone else v + shift.take(nth)
            self.fresh[key] = False
            reached.append(key)
            yield v, nth, tail, head
            counts = self.degree.take(v)
            ends = np.cumsum(counts)
            self.ops += len(v) + int(ends[-1])
            at = np.repeat(self.start.take(v) - ends + counts, counts)
            at += self._upto(len(at))
            to = self.near.take(at)
            if not lone:
                to += np.repeat(key - v, counts)
            new = np.flatnonzero(self.fresh.take(to))
            if not len(new):
                break
            to, tail = to.take(new), np.repeat(self._upto(len(v)), counts).take(new)
            head = self._upto(len(to))
            self.mark[to] = head
            first = self.mark.take(to) == head
            key = to[first]
            if lone:
                nth, v = np.zeros(len(key), np.int64), key
            else:
                nth = nth.take(tail[first])
                v = key - shift.take(nth)
            if links and len(key) < len(to):
                self.mark[key] = self._upto(len(key))
                head = self.mark.take(to)
        for key in reached:
            self.fresh[key] = True

    def dependencies(self, sources: np.ndarray, reach: np.ndarray, times: np.ndarray, total: np.ndarray) -> None:
        """Adds to ``total`` what the shortest paths from each source owe to each vertex but itself, ``times`` (of the source)
        over: path counts level by level, then dependencies from the deepest level back. ``reach``: how many targets a vertex
        stands for."""
        steps, sigma = [], np.ones(len(sources))
        for v, nth, tail, head in self.levels(sources, links=True):
            if tail is not None:
                sigma = np.bincount(head, sigma.take(tail), len(v))
            steps.append((v, nth, tail, head, sigma))
        delta = np.zeros(len(v))
        for k in range(len(steps) - 1, 1, -1):  # the sources, level 0, owe themselves nothing
            v, _, tail, head, sigma = steps[k]
            owed = (reach.take(v) + delta) / sigma
            v, nth, _, _, sigma = steps[k - 1]
            delta = sigma * np.bincount(tail, owed.take(head), len(v))
            if len(sources) > 1:
                np.add.at(total, v, delta * times.take(sources.take(nth)))
            else:
                total[v] += delta * times[sources[0]]
