"""Level plans: how p lanes split into nested groups, one factor per level."""

from __future__ import annotations

import math
from dataclasses import dataclass


@dataclass(frozen=True)
class LevelPlan:
    """``factors[i]`` parts per group at level i; their product is the number of lanes."""

    lanes: int
    factors: tuple[int, ...]

    def __post_init__(self):
        if math.prod(self.factors) != self.lanes or min(self.factors) < 1:
            raise ValueError(f"factors {self.factors} do not multiply to {self.lanes}")

    @property
    def group_sizes(self) -> list[int]:
        """Lanes of a group before each level."""
        out, size = [], self.lanes
        for r in self.factors:
            out.append(size)
            size //= r
        return out


def plan_single(p: int) -> LevelPlan:
    return LevelPlan(p, (p,))


def _split(p: int, k: int) -> tuple[int, ...]:
    """k factors as equal as the divisors of p allow, small ones first."""
    if k == 1:
        return (p,)
    root = round(p ** (1 / k), 9)
    best = max(d for d in range(1, int(root) + 1) if p % d == 0)
    return tuple(sorted((best, *_split(p // best, k - 1))))


def plan_equal(p: int, k: int) -> LevelPlan:
    """Factors near p^(1/k), last groups of one lane."""
    return LevelPlan(p, _split(p, k))


def plan_node_aligned(p: int, k: int, c: int) -> LevelPlan:
    """The last level stays inside one node of c lanes; fewer levels where p is too small for k of them."""
    while k > 1 and p < 2 ** (k - 1) * c:
        k -= 1
    if k == 1 or p % c:
        return plan_single(p)
    return LevelPlan(p, (*_split(p // c, k - 1), c))


def choose_levels(p: int, max_blocks: float = 5e8) -> int:
    """Fewest levels whose shuffle blocks (p per level times the factor, summed) stay within ``max_blocks``."""
    for k in (1, 2, 3, 4):
        if k * p * math.ceil(p ** (1 / k)) <= max_blocks:
            return k
    return 4


#: Defaults of every workload run: sampling by strings, oversampling v, assignment, front coding off, samples sorted by one
#: window (p (v + 1) rows), one hop per exchange.
DEFAULTS = {"sampling": "strings", "v": 2, "assign": "grid", "compress": False, "sample_sort": "window", "hops": 1}
