"""Structures that give the lightest block: the load ladder, the bucket queue and a heap for weights."""

from __future__ import annotations

import heapq


class LoadLadder:
    """Blocks in load order with one range per distinct load: raising a load by one and reading the lightest
    block take constant time, k blocks take O(k) memory."""

    def __init__(self, k: int, loads: list[int] | None = None):
        self.load = list(loads) if loads else [0] * k
        self.order = sorted(range(k), key=lambda b: (self.load[b], b))  # blocks, lightest first
        self.spot = [0] * k  # block -> its place in order
        self.range: dict[int, list[int]] = {}  # load -> first and last place
        for place, block in enumerate(self.order):
            self.spot[block] = place
            self.range.setdefault(self.load[block], [place, place])[1] = place

    def lightest(self) -> int:
        return self.order[0]

    def bump(self, block: int) -> None:
        old = self.load[block]
        here = self.range[old]
        end = here[1]
        other = self.order[end]
        at = self.spot[block]
        self.order[at], self.order[end] = other, block
        self.spot[other], self.spot[block] = at, end
        if end == here[0]:
            del self.range[old]
        else:
            here[1] = end - 1
        self.load[block] = old + 1
        above = self.range.get(old + 1)
        if above is None:
            self.range[old + 1] = [end, end]
        else:
            above[0] = end

    def ranges(self) -> list[tuple[int, int, int]]:
        """(load, first place, last place), lightest first."""
        return [(load, a, z) for load, (a, z) in sorted(self.range.items())]


class BucketQueue:
    """One slot per possible load: the same answers for O(k + capacity) memory."""

    def __init__(self, k: int, capacity: int):
        self.slots: list[dict[int, None]] = [dict() for _ in range(capacity + 1)]
        self.slots[0] = dict.fromkeys(range(k))
        self.load, self.low = [0] * k, 0

    def lightest(self) -> int:
        return next(iter(self.slots[self.low]))

    def bump(self, block: int) -> None:
        old = self.load[block]
        del self.slots[old][block]
        self.load[block] = old + 1
        self.slots[old + 1][block] = None
        while self.low < len(self.slots) - 1 and not self.slots[self.low]:
            self.low += 1


class LoadHeap:
    """Lightest by (load, id), for any positive increments; outdated entries are dropped when they surface."""

    def __init__(self, k: int):
        self.load: list[float] = [0] * k
        self.heap = [(0, b) for b in range(k)]

    def lightest(self) -> int:
        heap, load = self.heap, self.load
        while heap[0][0] != load[heap[0][1]]:
            heapq.heappop(heap)
        return heap[0][1]

    def bump(self, block: int, by: float = 1) -> None:
        if by:
            self.load[block] += by
            heapq.heappush(self.heap, (self.load[block], block))
