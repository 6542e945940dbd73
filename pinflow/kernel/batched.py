"""Rounds in one task: every vertex of a batch decides against the state before the batch, as plans.rounds does in parallel."""

from __future__ import annotations

import heapq

from ..params import PartitionSpec, penalty
from .greedy import Greedy


class Batched(Greedy):
    """Net states as in the one-pass rule; they and the loads move on after a whole batch."""

    def __init__(self, spec: PartitionSpec, capacity: int, strength: float):
        super().__init__(spec, capacity, strength)
        self.load = [0.0] * spec.k

    def wish(self, c: float, nets, light: int) -> int | None:
        """The best voted block that has room and beats the lightest one."""
        load, gamma, strength = self.load, self.spec.gamma, self.strength * c
        best = None
        for b, v in self.votes(nets).items():
            if load[b] + c <= self.capacity:
                key = (v - penalty(strength, gamma, load[b]), -load[b], -b)
                if best is None or key > best:
                    best = key
        if best is None or best <= (0.0 - penalty(strength, gamma, load[light]), -load[light], -light):
            return None
        return -best[2]

    def round(self, rows) -> list[int]:
        """Blocks of a batch's (weight, nets), which come in arrival order."""
        load, weighted = self.load, self.spec.weighted
        light = min(range(self.spec.k), key=lambda b: (load[b], b))
        blocks = [self.wish(c, nets, light) for c, nets in rows]
        asked: dict[int, float] = {}
        for (c, _), b in zip(rows, blocks):
            if b is not None:
                asked[b] = asked.get(b, 0.0) + c
        room = {b: self.capacity - load[b] for b, c in asked.items() if load[b] + c > self.capacity}
        met = dict.fromkeys(room, 0.0)
        for i, b in enumerate(blocks):
            if b is None:
                continue
            if b in room:  # a block that has not room for all takes them by arrival
                met[b] += rows[i][0] if weighted else 1.0
                if met[b] > (room[b] if weighted else int(room[b])):
                    blocks[i] = None
                    continue
            load[b] += rows[i][0]
        if None in blocks:
            heap = [(x if weighted else int(x), b) for b, x in enumerate(load)]
            heapq.heapify(heap)
            for i, b in enumerate(blocks):
                if b is None:
                    at, b = heap[0]
                    if not weighted and at >= self.capacity:
                        raise ValueError("no block has a free place")
                    heapq.heapreplace(heap, (at + (rows[i][0] if weighted else 1), b))
                    blocks[i] = b
            self.load = [float(x) for x, _ in sorted(heap, key=lambda x: x[1])]
        for (_, nets), b in zip(rows, blocks):
            self.settle(nets, b)
        return blocks
