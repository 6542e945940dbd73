"""One-pass greedy rules: per arriving vertex, votes of its nets against a load penalty."""

from __future__ import annotations

from ..params import PartitionSpec, penalty
from .ladder import BucketQueue, LoadHeap, LoadLadder


class Greedy:
    """Places vertices one by one. State: a load per block and, per net, the block of its latest pin and whether it is cut.

    engine: 'split' scores voted blocks and stands the lightest block for all others; 'scan' scores all blocks."""

    def __init__(self, spec: PartitionSpec, capacity: int, strength: float, engine: str = "split", index: str | None = None):
        self.spec, self.capacity, self.strength, self.engine = spec, capacity, strength, engine
        index = index or ("ladder" if spec.tie == "ladder" else "heap")
        self.index = LoadLadder(spec.k) if index == "ladder" else BucketQueue(spec.k, capacity) if index == "queue" else LoadHeap(spec.k)
        self.last: dict[int, int] = {}  # net -> block * 2 + cut
        self.cut_only = spec.objective == "cut"
        self.evaluations = 0

    def votes(self, nets) -> dict[int, float]:
        found: dict[int, float] = {}
        last, cut_only = self.last, self.cut_only
        for net, weight in nets:
            state = last.get(net)
            if state is None or (cut_only and state & 1):
                continue
            block = state >> 1
            found[block] = found.get(block, 0.0) + weight
        return found

    def choose(self, votes: dict[int, float], c: float) -> tuple[int, float, float, str]:
        """(block, affinity, score, source): the best score; equal scores go to the lighter, then the smaller block."""
        load, room, gamma, strength = self.index.load, self.capacity - c, self.spec.gamma, self.strength * c
        if self.engine == "scan":
            best = None
            for b in range(self.spec.k):
                self.evaluations += 1
                if load[b] <= room:
                    v = votes.get(b, 0.0)
                    key = (v - penalty(strength, gamma, load[b]), -load[b], -b)
                    if best is None or key > best[0]:
                        best = (key, b, v)
            if best is None:
                return self.index.lightest(), 0.0, 0.0, "overflow"
            return best[1], best[2], best[0][0], "touched" if best[1] in votes else "untouched"
        best, light = None, self.index.lightest()
        for b, v in votes.items():
            if load[b] <= room:
                self.evaluations += 1
                key = (v - penalty(strength, gamma, load[b]), -load[b], -b)
                if best is None or key > best[0]:
                    best = (key, b, v)
        if light not in votes or load[light] > room:
            if load[light] > room:
                if best is None:
                    return light, 0.0, 0.0, "overflow"
            else:
                self.evaluations += 1
                key = (-penalty(strength, gamma, load[light]), -load[light], -light)
                if best is None or key > best[0]:
                    return light, 0.0, key[0], "untouched"
        return best[1], best[2], best[0][0], "touched"

    def settle(self, nets, block: int) -> None:
        last = self.last
        for net, _ in nets:
            state = last.get(net)
            last[net] = block << 1 if state is None else block << 1 | (state & 1 or state >> 1 != block)

    def place(self, c: float, nets) -> tuple[int, float, float, str, int, int]:
        votes, before = self.votes(nets), self.evaluations
        block, affinity, score, source = self.choose(votes, c)
        if isinstance(self.index, LoadHeap):
            self.index.bump(block, c)
        else:
            self.index.bump(block)
        self.settle(nets, block)
        return block, affinity, score, source, len(votes), self.evaluations - before


class GraphGreedy(Greedy):
    """The graph rule: votes are placed neighbours. Keeps an assignment instead of net states."""

    def votes(self, nets) -> dict[int, float]:
        found: dict[int, float] = {}
        for neighbour, weight in nets:
            block = self.last.get(neighbour)
            if block is not None:
                found[block] = found.get(block, 0.0) + weight
        return found

    def settle(self, nets, block: int) -> None:
        pass

    def place_vertex(self, vertex: int, c: float, neighbours) -> tuple[int, float, float, str, int, int]:
        placed = self.place(c, neighbours)
        self.last[vertex] = placed[0]
        return placed


class MultiSection:
    """Places down a tree of groups: cost follows its depth and fanout, not k. Leaves are blocks, in order."""

    def __init__(self, spec: PartitionSpec, capacity: int, strength: float, fanout: int):
        self.spec, self.capacity, self.strength, self.fanout = spec, capacity, strength, fanout
        self.load: dict[tuple[int, int], float] = {}  # (first leaf, leaves) -> load
        self.last: dict[int, int] = {}

    def place(self, c: float, nets) -> tuple[int, float, float, str, int, int]:
        pulls: dict[int, float] = {}
        for net, weight in nets:
            state = self.last.get(net)
            if state is not None and not (self.spec.objective == "cut" and state & 1):
                pulls[state >> 1] = pulls.get(state >> 1, 0.0) + weight
        first, leaves, affinity, score, source = 0, self.spec.k, 0.0, 0.0, "section"
        while leaves > 1:
            parts = min(self.fanout, leaves)
            best = None
            for i in range(parts):
                a, z = first + leaves * i // parts, first + leaves * (i + 1) // parts
                load = self.load.get((a, z - a), 0.0)
                fits = load + c <= self.capacity * (z - a)
                v = sum(w for b, w in pulls.items() if a <= b < z)
                # Where no part has room, the one filled least takes the vertex.
                key = (fits, v - c * penalty(self.strength, self.spec.gamma, load / (z - a)) if fits else 0.0, -load / (z - a), -a)
                if best is None or key > best[0]:
                    best = (key, a, z - a, v)
            _, first, leaves, affinity = best
            score = best[0][1]
            if not best[0][0]:
                source = "overflow"
            self.load[first, leaves] = self.load.get((first, leaves), 0.0) + c
        for net, _ in nets:
            state = self.last.get(net)
            self.last[net] = first << 1 if state is None else first << 1 | (state & 1 or state >> 1 != first)
        return first, affinity, score, source, len(pulls), 0
