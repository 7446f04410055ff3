"""Metrics, each as a NumPy kernel (one center against many points) and as a Column expression.

The kernels give an *order key*: a monotone function of the distance that is exact on integer
coordinates (the squared distance for ``euclidean``). ``finish`` turns keys into distances.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Metric:
    name: str
    kernel: Callable[[np.ndarray, np.ndarray], np.ndarray]
    expr: Callable[[Column, list[float]], Column]
    finish: Callable[[float], float] = float
    finish_expr: Callable[[Column], Column] = lambda c: c


def _parts(point: Column, center: list[float]) -> list[Column]:
    return [point[i] - F.lit(float(v)) for i, v in enumerate(center)]


def _total(parts: list[Column]) -> Column:
    out = parts[0]
    for p in parts[1:]:
        out = out + p
    return out


def _squared(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    out = np.zeros(len(x))
    for j in range(x.shape[1]):
        d = x[:, j] - c[j]
        d *= d
        out += d
    return out


def _arc(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    cos = (x @ c) / (np.linalg.norm(x, axis=1) * np.linalg.norm(c))
    return np.arccos(np.clip(cos, -1.0, 1.0))


def _haversine(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    a, b = np.radians(x), np.radians(c)
    h = np.sin((a[:, 0] - b[0]) / 2) ** 2 + np.cos(a[:, 0]) * np.cos(b[0]) * np.sin((a[:, 1] - b[1]) / 2) ** 2
    return 2 * np.arcsin(np.sqrt(np.clip(h, 0, 1)))


def _haversine_expr(p: Column, c: list[float]) -> Column:
    lat = F.radians(p[0])
    h = F.pow(F.sin((lat - math.radians(c[0])) / 2), 2) + F.cos(lat) * math.cos(math.radians(c[0])) * F.pow(F.sin((F.radians(p[1]) - math.radians(c[1])) / 2), 2)
    return 2 * F.asin(F.sqrt(F.least(h, F.lit(1.0))))


def _jaccard(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    a, b = x > 0, c > 0
    both, any_ = (a & b).sum(1), (a | b).sum(1)
    return np.where(any_ == 0, 0.0, 1.0 - both / np.maximum(any_, 1))


def _jaccard_expr(p: Column, c: list[float]) -> Column:
    both = _total([F.lit(0)] + [(p[i] > 0).cast("int") for i, v in enumerate(c) if v > 0])
    any_ = _total([F.lit(0)] + [F.lit(1) if v > 0 else (p[i] > 0).cast("int") for i, v in enumerate(c)])
    return F.when(any_ == 0, F.lit(0.0)).otherwise(1.0 - both / any_)


def minkowski(p: float) -> Metric:
    """The Minkowski metric, p >= 1; keys are sums of p-th powers."""
    if p < 1:
        raise ValueError("p below 1 is no metric")
    return Metric(
        f"minkowski{p:g}", lambda x, c: (np.abs(x - c) ** p).sum(1), lambda x, c: _total([F.pow(F.abs(d), F.lit(p)) for d in _parts(x, c)]),
        lambda v: v ** (1 / p), lambda v: F.pow(v, F.lit(1 / p)),
    )


METRICS: dict[str, Metric] = {
    m.name: m
    for m in (
        Metric("euclidean", _squared, lambda x, c: _total([d * d for d in _parts(x, c)]), math.sqrt, F.sqrt),
        Metric("manhattan", lambda x, c: np.abs(x - c).sum(1), lambda x, c: _total([F.abs(d) for d in _parts(x, c)])),
        Metric("chebyshev", lambda x, c: np.abs(x - c).max(1), lambda x, c: F.greatest(F.lit(0.0), *[F.abs(d) for d in _parts(x, c)])),
        Metric("hamming", lambda x, c: (x != c).sum(1).astype(float), lambda x, c: _total([(x[i] != F.lit(float(v))).cast("double") for i, v in enumerate(c)])),
        Metric("discrete", lambda x, c: (x != c).any(1).astype(float), lambda x, c: (x != F.array(*[F.lit(float(v)) for v in c])).cast("double")),
        Metric("angular", _arc, lambda x, c: F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), _total([x[i] * float(v) for i, v in enumerate(c)]) / (F.sqrt(_total([x[i] * x[i] for i in range(len(c))])) * math.sqrt(sum(v * v for v in c))))))),
        Metric("haversine", _haversine, _haversine_expr),
        Metric("jaccard", _jaccard, _jaccard_expr),
    )
}


def metric(which: str | Metric) -> Metric:
    return which if isinstance(which, Metric) else METRICS[which]
