"""Parameters of all partitioning methods and the closed forms they share."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace
from fractions import Fraction


@dataclass(frozen=True)
class PartitionParams:
    """k blocks of imbalance eps; delta: vertices a buffer (None: the whole graph in one model).

    model: 'basic' ignores later neighbours, 'extended' folds them into buffer vertices. x: coarsest-size factor.
    objective: 'penalty_gain' (connection minus convex load penalty) or 'capacity_discount' (connection times free share).
    budget: if given, a buffer closes when the sum of 1 + degree passes it, whatever delta says (a hub fills one by itself).
    alpha_basis: 'count' takes vertex and edge counts, 'weight' their weights. tie: 'random' (seeded) or 'lowest'.
    engine: 'fold', 'driver_loop', 'lanes' (of `lanes` concurrent buffers), 'distributed' (coarsened by DataFrame rounds).
    """

    k: int
    eps: float = 0.03
    delta: int | None = 32768
    budget: int | None = None
    model: str = "extended"
    x: int = 4
    coarsen_rounds: int = 5
    refine_rounds: int = 5
    passes: int = 1
    gamma: float = 1.5
    alpha: float | None = None
    alpha_basis: str = "count"
    objective: str = "penalty_gain"
    cluster_factor: int = 14
    order: str = "natural"
    tie: str = "random"
    seed: int = 42
    power: str = "exact"
    engine: str = "fold"
    lanes: int = 1
    initial: str = "greedy"

    def __post_init__(self):
        if self.k < 1 or self.eps < 0 or (self.delta is not None and self.delta < 1):
            raise ValueError("k and delta must be positive and eps not negative")
        for name, allowed in (("model", ("basic", "extended")), ("objective", ("penalty_gain", "capacity_discount")), ("tie", ("random", "lowest")), ("engine", ("fold", "driver_loop", "lanes", "distributed")), ("power", ("exact", "table")), ("initial", ("greedy", "recursive_bisection")), ("order", ("natural", "degree", "random"))):
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} must be one of {allowed}")

    def with_(self, **changes) -> PartitionParams:
        return replace(self, **changes)


def lmax(total: float, k: int, eps: float) -> float:
    """Largest load of a block, ceil((1 + eps) total / k); exact where total is whole."""
    if float(total).is_integer():
        return float(math.ceil((1 + Fraction(str(eps))) * int(total) / k))
    return float(math.ceil((1 + eps) * total / k))


def alpha(n: float, m: float, k: int, gamma: float) -> float:
    """Scale of the load penalty: m k^(gamma-1) / n^gamma; for gamma 1.5 in square roots, which all engines round alike."""
    if n <= 0:
        return 0.0
    if gamma == 1.5:
        return math.sqrt(k) * m / (n * math.sqrt(n))
    return m * k ** (gamma - 1) / n**gamma
