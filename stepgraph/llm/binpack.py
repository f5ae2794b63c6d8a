"""Best-fit-decreasing bin packing; open bins stand in a balanced tree by what they still hold."""

from __future__ import annotations

from collections.abc import Sequence


class RoomTree:
    """A treap of (room, bin); priorities come from a fixed mix of the bin's number, so runs agree."""

    def __init__(self) -> None:
        self.root: list | None = None  # [room, bin, priority, left, right]

    @staticmethod
    def _priority(room: int, b: int) -> int:
        x = (b * 0x9E3779B97F4A7C15 ^ room * 0xBF58476D1CE4E5B9) & 0xFFFFFFFFFFFFFFFF
        return (x ^ x >> 31) * 0x94D049BB133111EB & 0xFFFFFFFFFFFFFFFF

    def _split(self, node: list | None, key: tuple[int, int]) -> tuple[list | None, list | None]:
        if node is None:
            return None, None
        if (node[0], node[1]) < key:
            node[4], right = self._split(node[4], key)
            return node, right
        left, node[3] = self._split(node[3], key)
        return left, node

    def _merge(self, a: list | None, b: list | None) -> list | None:
        if a is None or b is None:
            return a or b
        if a[2] > b[2]:
            a[4] = self._merge(a[4], b)
            return a
        b[3] = self._merge(a, b[3])
        return b

    def add(self, room: int, b: int) -> None:
        left, right = self._split(self.root, (room, b))
        self.root = self._merge(self._merge(left, [room, b, self._priority(room, b), None, None]), right)

    def take_tightest(self, size: int) -> tuple[int, int] | None:
        """Removes and returns the (room, bin) of least room that holds ``size``."""
        left, right = self._split(self.root, (size, -1))
        if right is None:
            self.root = left
            return None
        at, above = right, None
        while at[3] is not None:
            at, above = at[3], at
        if above is None:
            right = at[4]
        else:
            above[3] = at[4]
        self.root = self._merge(left, right)
        return at[0], at[1]


def best_fit_decreasing(sizes: Sequence[int], capacity: int, order: Sequence[int] | None = None) -> tuple[list[int], int]:
    """Bin of each item and how many bins; an item above the capacity has a bin of its own."""
    tree, bins, out = RoomTree(), 0, [0] * len(sizes)
    for i in order if order is not None else sorted(range(len(sizes)), key=lambda i: (-sizes[i], i)):
        got = tree.take_tightest(sizes[i])
        if got is None:
            got, bins = (max(capacity, sizes[i]), bins), bins + 1
        out[i] = got[1]
        tree.add(got[0] - sizes[i], got[1])
    return out, bins


def pack_counts(items: Sequence[tuple[int, int]], capacity: int, most: int | None = None) -> tuple[list[tuple[int, int, int]], int]:
    """The same of (size, count), sizes falling, in steps of a bin and not of an item: what enters the tightest bin leaves it
    the tightest, until it holds no more of that size. Returns runs (size, first, bin): from the ``first`` item of a size on,
    they are in that bin, up to the next run; and how many bins, where more than ``most`` end it early."""
    tree, bins, runs = RoomTree(), 0, []
    for size, count in items:
        first = 0
        while first < count:
            got = tree.take_tightest(size)
            if got is None:
                if bins == most:
                    return runs, bins + 1
                got, bins = (max(capacity, size), bins), bins + 1
            room, b = got
            fit = min(count - first, room // size)
            runs.append((size, first, b))
            first += fit
            tree.add(room - fit * size, b)
    return runs, bins


def counts_into_bins(items: Sequence[tuple[int, int]], bins: int) -> list[tuple[int, int, int]]:
    """Runs for a given number of bins: at the least capacity, found by bisection to a millionth, at which they suffice."""
    if not items:
        return []
    total, largest = sum(s * c for s, c in items), items[0][0]
    low = max(-(-total // bins), largest)
    high = low + largest  # a bin that takes no more of an item is fuller than the mean, so this many bytes are enough
    while high - low > low >> 20:
        mid = (low + high) // 2
        if pack_counts(items, mid, bins)[1] <= bins:
            high = mid
        else:
            low = mid + 1
    return pack_counts(items, high, bins)[0]
