"""Accuracy bounds of pivot sampling: which pivot factors keep the factor-10 guarantee, and how surely."""

from __future__ import annotations

import math

#: The pivot-factor bound as published (fixed value); phi_threshold computes it from its inequality.
PRINTED_PHI_BOUND = 5.15


def feasible_acd(phi: float, x: float = 1.0) -> float:
    """The largest a c d for which too few probes above the pivot are unlikely."""
    return phi + x / 2 - math.sqrt(2 * x * phi + x * x / 4)


def feasible_bcd(phi: float, x: float = 1.0) -> float:
    """The smallest b c d for which too many are unlikely."""
    return phi + x + math.sqrt(2 * x * phi + x * x)


def phi_holds(phi: float, b: float = 5.0, x: float = 1.0) -> bool:
    """Whether the interval between both bounds is wide enough for the shrink factor b."""
    return b * feasible_acd(phi, x) >= feasible_bcd(phi, x)


def phi_threshold(b: float = 5.0, x: float = 1.0) -> float:
    """The smallest pivot factor that is feasible for shrink factor b, by bisection."""
    lo, hi = x, 1e6
    if not phi_holds(hi, b, x):
        raise ValueError("no pivot factor is feasible")
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (lo, mid) if phi_holds(mid, b, x) else (mid, hi)
    return hi


def success_probability(n: int, gamma: float = 0.0) -> float:
    """At least 1 - 2 n^-(1 + gamma) for one iteration."""
    return max(0.0, 1 - 2 * n ** -(1 + gamma))


def gamma_of(n: int) -> float:
    """log log n / log n, with which all iterations together fail with probability O(1 / log n)."""
    return math.log(math.log(n)) / math.log(n)


def mapping_condition(n: int, eps: float, b: float = 5.0) -> bool:
    """b / n^eps < 2, which the mapping of unsatisfied points needs."""
    return b / n**eps < 2


def unsatisfied_bound(live: int, n: int, eps: float) -> float:
    """More unsatisfied live points than this have probability at most n^-2."""
    return live / (3 * n**eps)


def shrink_bounds(live: int, n: int, eps: float, a: float = 1.0, b: float = 5.0) -> tuple[float, float]:
    """Where the next live set's size lies with high probability at the published pivot rank."""
    return a * live / n**eps, b * live / n**eps


def satisfied_subset_factor() -> int:
    """Centers taken from the sample alone can cost this many times the optimum."""
    return 5


def guarantee(algorithm: str, rounds: int = 2, alpha: float = 2.0) -> float:
    """Approximation factor: farthest_first, blocked (by rounds), pivot_sampling (by its final solver)."""
    return {"farthest_first": 2.0, "blocked": 2.0 * rounds, "pivot_sampling": 4 * alpha + 2}[algorithm]
