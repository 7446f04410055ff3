"""Covers by balls: the bottleneck 2-approximation for small sets, and the cover for a known radius."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

from farpoint.functions.distance import Metric, metric
from farpoint.operators import kernels
from farpoint.operators.farthest_first import CENTERS, center_batch, gathered

#: Points whose pairwise distances (8 bytes a pair) are held; of more points they are searched for.
HELD = 2_000
#: Points of a box in that search.
LEAF = 256


def greedy_cover(x: np.ndarray, key: float, most: int, measure: str | Metric = "euclidean") -> np.ndarray | None:
    """Uncovered points in order become centers of balls of that key; None if ``most`` do not do."""
    m, open_, picks = metric(measure), np.ones(len(x), bool), []
    while open_.any():
        if len(picks) == most:
            return None
        i = int(np.argmax(open_))
        picks.append(i)
        open_ &= m.kernel(x, x[i]) > key
    return np.array(picks, np.int64)


def threshold_solver(x: np.ndarray, k: int, seed: int = 0, measure: str = "euclidean") -> tuple[np.ndarray, np.ndarray, float]:
    """The least pairwise distance r, as a search finds it, with a cover by k balls of radius 2 r.

    Twice the optimum at most; a solver for blocks and final rounds. Up to HELD points the distances are sorted and searched;
    of more points the least number with a cover is found by bisection, then the next distance from it.
    """
    m = metric(measure)
    twice = 4.0 if m.name == "euclidean" else 2.0
    picks = _held(x, k, twice, measure) if len(x) <= HELD else _bisected(x, k, twice, measure)
    _, low = kernels.nearest(x, x[picks], measure)
    return picks, np.full(len(picks), np.inf), float(low.max())


def _held(x: np.ndarray, k: int, twice: float, measure: str | Metric) -> np.ndarray:
    m = metric(measure)
    keys = np.unique(np.concatenate([m.kernel(x[i:], x[i]) for i in range(len(x))]))
    lo, hi = 0, len(keys) - 1
    while lo < hi:
        mid = (lo + hi) // 2
        if greedy_cover(x, twice * keys[mid], k, measure) is not None:
            hi = mid
        else:
            lo = mid + 1
    return greedy_cover(x, twice * keys[lo], k, measure)


def _bisected(x: np.ndarray, k: int, twice: float, measure: str | Metric) -> np.ndarray:
    """``_held`` without the distances. A number without a cover is below the optimum, so the next distance is at most the optimum."""
    picks = greedy_cover(x, 0.0, k, measure)
    if picks is not None:
        return picks
    lo, most = 0.0, kernels.farthest_first(x, k, 0, 0.0, measure)[2]  # at farthest-first's radius, or the optimum, there is a cover
    places = np.unique(x, axis=0)
    while True:
        low, high = (int(np.array(v).view(np.int64)) for v in (lo, most))  # numbers from 0 on are in the order of their bits
        while low + 1 < high:
            mid = (low + high) // 2
            if greedy_cover(x, twice * float(np.array(mid).view(np.float64)), k, measure) is not None:
                high = mid
            else:
                low = mid
        r = next_key(places, float(np.array(high).view(np.float64)), measure)
        picks = greedy_cover(x, twice * r, k, measure)
        if picks is not None:
            return picks
        lo = r  # covers need not stay when balls grow


def next_key(x: np.ndarray, least: float, measure: str | Metric = "euclidean") -> float:
    """The smallest key of two points that is not below ``least`` (infinite where there is none), looking at all pairs that may have it."""
    m, best = metric(measure), np.inf
    for i in range(0, len(x), max(1, len(x) // 64)):  # a first bound
        key = m.kernel(x, x[i])
        best = min(best, float(key[key >= least].min(initial=np.inf)))
    if m.name != "euclidean":
        for i in range(len(x)):
            key = m.kernel(x[i:], x[i])
            best = min(best, float(key[key >= least].min(initial=np.inf)))
        return best
    leaves = kernels.halved(x, LEAF)
    lows, highs = np.array([x[rows].min(0) for rows in leaves]), np.array([x[rows].max(0) for rows in leaves])
    for a, rows in enumerate(leaves):
        gap = np.maximum(0.0, np.maximum(lows[a:] - highs[a], lows[a] - highs[a:]))
        span = np.maximum(highs[a:] - lows[a], highs[a] - lows[a:])
        near, wide = (gap * gap).sum(1) * (1 - 1e-12), (span * span).sum(1) * (1 + 1e-12)
        for b in a + np.flatnonzero((near < best) & (wide >= least)):
            if best == least:
                return best
            key = np.zeros((len(rows), len(leaves[b])))
            for j in range(x.shape[1]):
                d = x[rows, j][:, None] - x[leaves[b], j][None]
                d *= d
                key += d
            best = min(best, float(key[key >= least].min(initial=np.inf)))
    return best


def threshold_cover(points: DataFrame, k: int, measure: str = "euclidean") -> DataFrame:
    """Centers (rank, id, coords, key null) of the bottleneck method, in one task."""

    def run(batches):
        ids, x = gathered(batches)
        if len(ids):
            picks, keys, _ = threshold_solver(x, k, 0, measure)
            yield center_batch(ids, x, picks, keys)

    return points.select("id", "coords").repartition(1).mapInArrow(run, CENTERS)


def known_opt_cover(points: DataFrame, key: float, measure: str = "euclidean") -> DataFrame:
    """Centers of a greedy cover by balls of a given key, as many as it takes (extension)."""

    def run(batches):
        ids, x = gathered(batches)
        if len(ids):
            picks = greedy_cover(x, key, len(x), measure)
            yield center_batch(ids, x, picks, np.full(len(picks), np.inf))

    return points.select("id", "coords").repartition(1).mapInArrow(run, CENTERS)
