"""Cost model in distance evaluations, and the exact counters that check it."""

from __future__ import annotations

import math


def cost_farthest_first(n: int, k: int) -> float:
    return float(k * n)


def cost_blocked(n: int, k: int, m: int) -> float:
    """Slowest machine: its block in round one, all blocks' centers in round two."""
    return k * n / m + k * k * m


def cost_sampling(n: int, k: int, m: int, eps: float, log_base: float = math.e) -> float:
    """The pruning rounds, which dominate."""
    log_n = math.log(n) / math.log(log_base)
    return k * n ** (1 + eps) * log_n / (m * (1 - n**-eps) ** 2)


def cost_sampling_rounds(n: int, k: int, m: int, eps: float, log_base: float = math.e) -> dict[str, float]:
    """Published cost of each kind of round, summed over the iterations."""
    log_n, g = math.log(n) / math.log(log_base), n**eps
    return {
        "draws": n / (m * (1 - 1 / g)), "pivot": (k / eps**2) * (g * log_n) ** 2, "prune": cost_sampling(n, k, m, eps, log_base), "final": (k * k / eps) * g * log_n,
        "final_with_rest": (k * k / eps) * g * log_n + k * (4 / eps) * k * g * log_n,  # the output also holds what stayed live
    }


def predict_slowdown(n: int, eps: float = 0.1, log_base: float = math.e) -> float:
    """Pivot sampling over the blocked scheme."""
    return n**eps * (1 - n**-eps) ** -2 * math.log(n) / math.log(log_base)


def predict_cost(algorithm: str, n: int, k: int, m: int = 1, eps: float = 0.1, log_base: float = math.e) -> float:
    if algorithm == "farthest_first":
        return cost_farthest_first(n, k)
    if algorithm == "blocked":
        return cost_blocked(n, k, m)
    if algorithm == "pivot_sampling":
        return cost_sampling(n, k, m, eps, log_base)
    raise ValueError(algorithm)


def count_farthest_first(n: int, k: int) -> int:
    return k * n


def count_blocked(block_sizes: list[int], k: int) -> dict[str, int]:
    """Exact evaluations of the two-round scheme: by round, in total and on the slowest machine."""
    first = [min(k, n) * n for n in block_sizes]
    union = sum(min(k, n) for n in block_sizes)
    last = min(k, union) * union
    return {"round_1": sum(first), "round_2": last, "total": sum(first) + last, "slowest": max(first, default=0) + last}


def count_sampling(trace: list[dict], m: int, sample_size: int, k: int, incremental: bool = True) -> dict[str, int]:
    """From a trace: point visits of the draws, probe distances, pruning distances, final traversal."""
    draws = pivot = prune = members = 0
    for t in trace:
        members += t["new_sample"]
        share = -(-t["live"] // m)
        draws += share
        pivot += t["probes"] * members
        prune += share * (t["new_sample"] if incremental else members)
    return {"draws": draws, "pivot": pivot, "prune": prune, "final": k * sample_size}


def rounds(algorithm: str, iterations: int = 0, levels: int = 1) -> int:
    """Parallel rounds: a level each and one more; three for each sampling iteration and one more."""
    return {"farthest_first": 1, "blocked": levels + 1, "pivot_sampling": 3 * iterations + 1}[algorithm]
