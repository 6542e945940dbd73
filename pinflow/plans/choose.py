"""Which lane a hypergraph takes."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..operators.shape import Hypergraph
from ..params import PartitionSpec
from . import ordered, rounds

BYTES_PER_NET = 120  # a dictionary entry of the kernel
TASK_BYTES = 4 << 30
PIN_LIMIT = 10**9  # about half an hour of one task


def lane(stats: dict, spec: PartitionSpec, task_bytes: int = TASK_BYTES, pin_limit: int = PIN_LIMIT) -> str:
    """'ordered' where one task can hold the net states and walk the pins, else 'rounds'."""
    fits = stats["m"] * BYTES_PER_NET + spec.k * 200 <= task_bytes
    return "ordered" if fits and stats["pins"] <= pin_limit else "rounds"


def place(h: Hypergraph, spec: PartitionSpec, **limits) -> DataFrame:
    """vertex_id, block by the lane that the hypergraph's size asks for."""
    if lane(h.stats(), spec, **limits) == "ordered":
        return ordered.assign(h, spec)
    return rounds.greedy(h, spec).select("vertex_id", "block")
