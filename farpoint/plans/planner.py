"""Capacity planning of the blocked scheme: blocks, levels, guarantees."""

from __future__ import annotations

import math
from dataclasses import dataclass


class CapacityStall(ValueError):
    """The number of blocks no longer falls: centers of the last level do not fit into one task."""


@dataclass(frozen=True)
class Level:
    points: int
    blocks: int
    out: int


@dataclass(frozen=True)
class LevelPlan:
    levels: tuple[Level, ...]
    final_points: int

    @property
    def rounds(self) -> int:
        return len(self.levels) + 1

    @property
    def guarantee(self) -> int:
        """Each round adds twice the optimum."""
        return 2 * self.rounds


def blocks_for(n: int, k: int, m: int) -> int:
    """At most m blocks, fewer where a block would not hold more points than centers."""
    return max(1, min(m, -(-n // (k + 1)) if n > k else 1))


def plan_levels(n: int, k: int, m: int, capacity: int, rounds: int | None = None) -> LevelPlan:
    """Levels until the centers fit into one task (``capacity`` points); ``rounds`` forces their number."""
    if k > capacity:
        raise CapacityStall(f"{k} centers do not fit into a task of {capacity} points")
    if -(-n // m) > capacity:
        raise CapacityStall(f"a block of {-(-n // m)} points does not fit into a task of {capacity} points")
    if n <= k:
        return LevelPlan((), n)
    levels, points, blocks = [], n, blocks_for(n, k, m)
    while (points > capacity if rounds is None else len(levels) < rounds - 1) or not levels:
        if rounds == 1:
            break
        out = min(points, k * blocks)
        levels.append(Level(points, blocks, out))
        now = -(-out // capacity) if rounds is None else max(1, blocks // 2)
        if rounds is None and out > capacity and now >= blocks:
            raise CapacityStall(f"{blocks} blocks give {out} centers, which need {now} blocks again")
        points, blocks = out, blocks_for(out, k, now)
    return LevelPlan(tuple(levels), points)


def block_counts(k: int, m: int, capacity: int) -> list[int]:
    """m, then ceil(k m / c) again and again down to 1."""
    out = [m]
    while out[-1] > 1:
        now = -(-k * out[-1] // capacity)
        if now >= out[-1]:
            raise CapacityStall(f"stays at {now} blocks: {out}")
        out.append(now)
    return out


def machines_bound(m: int, k: int, capacity: int, i: int) -> float:
    """The closed form that block_counts stays below after i rounds."""
    q = k / capacity
    return m * q**i + (i if q == 1 else (1 - q**i) / (1 - q))


def capacity_needed(n: int, k: int, m: int) -> int:
    """Points that the fullest task of the two-round scheme holds."""
    return max(-(-n // m), k * m)


def feasibility(n: int, k: int, m: int, capacity: int) -> dict[str, bool]:
    return {
        "block_fits": -(-n // m) <= capacity, "union_fits": k * m <= capacity, "stored": m * capacity >= n, "centers_fit": k <= capacity,
        "two_rounds": -(-n // m) <= capacity and k * m <= capacity,
    }


def balanced_m(n: int, k: int) -> int:
    """The number of blocks that makes both rounds of the two-round scheme equally long."""
    return max(1, round(math.sqrt(n / k)))
