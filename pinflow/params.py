"""Parameters of a partition and what follows from them."""

from __future__ import annotations

import math
from dataclasses import dataclass
from fractions import Fraction


@dataclass(frozen=True)
class PartitionSpec:
    """k blocks of at most ceil((1 + eps) * total / k); eps is a decimal string so that the bound is exact."""

    k: int
    eps: str = "0.03"
    objective: str = "con"  # 'con' or 'cut'
    gamma: float = 1.5
    alpha: float | None = None
    alpha_scale: float = 1.0
    tie: str = "lowest_id"  # or 'ladder'
    weighted: bool = False
    seed: int = 0

    def __post_init__(self):
        if self.k < 1:
            raise ValueError("k must be positive")
        if self.objective not in ("con", "cut"):
            raise ValueError("objective is 'con' or 'cut'")
        if self.gamma < 1 or (self.alpha is not None and self.alpha < 0) or self.alpha_scale < 0:
            raise ValueError("the penalty must not fall with the load: gamma >= 1, alpha >= 0")
        if self.tie not in ("lowest_id", "ladder"):
            raise ValueError("tie is 'lowest_id' or 'ladder'")
        if self.tie == "ladder" and self.weighted:
            raise ValueError("the ladder holds whole loads that grow by one; weighted vertices use 'lowest_id'")
        if Fraction(self.eps) < 0:
            raise ValueError("eps must not be negative")

    def capacity(self, total: float) -> int:
        """The bound, in exact arithmetic."""
        return math.ceil((1 + Fraction(self.eps)) * Fraction(total) / self.k)

    def strength(self, n: float, m: float) -> float:
        """alpha * gamma, once, as the double that every engine shares. n, m: vertices and nets, or their weights."""
        alpha = self.alpha
        if alpha is None:
            alpha = math.sqrt(self.k) * m / (n * math.sqrt(n)) if n else 0.0
        return self.gamma * (alpha * self.alpha_scale)


def penalty(strength: float, gamma: float, load: float) -> float:
    """alpha * gamma * load ** (gamma - 1)."""
    if gamma == 1.5:
        return strength * math.sqrt(load)
    return strength * (1.0 if gamma == 1 else load if gamma == 2 else load ** (gamma - 1))
