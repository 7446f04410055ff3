"""Synthetic point sets of any size, made by hashing the row number: any partitioning gives the same points."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from farpoint.functions.hashing import fast_uniform


def _normal(seed: int, tag: str, key: Column) -> Column:
    return F.sqrt(-2 * F.log(1 - fast_uniform(seed, tag + "r", key))) * F.cos(2 * math.pi * fast_uniform(seed, tag + "t", key))


def uniform_square(spark: SparkSession, n: int, side: float = 100.0, seed: int = 1, dims: int = 2, scale: float | None = None) -> DataFrame:
    """Points uniform in a square (or cube)."""
    rows = spark.range(n)
    return rows.select("id", F.array(*[_fixed(side * fast_uniform(seed, f"u{i}", F.col("id")), scale) for i in range(dims)]).alias("coords"))


def gaussian_clusters(spark: SparkSession, n: int, groups: int, sigma: float = 0.1, dims: int = 3, side: float = 100.0, seed: int = 1, scale: float | None = None, offset: str = "axis") -> DataFrame:
    """id, coords, g: equal groups around uniform centers."""
    return _around(spark.range(n).withColumn("g", F.pmod("id", F.lit(groups))), sigma, dims, side, seed, scale, offset)


def skewed_clusters(spark: SparkSession, n: int, groups: int, heavy: float = 0.5, sigma: float = 0.1, dims: int = 3, side: float = 100.0, seed: int = 1, scale: float | None = None, offset: str = "axis") -> DataFrame:
    """id, coords, g: about the share ``heavy`` of the points is in group 0."""
    g = F.when(fast_uniform(seed, "heavy", F.col("id")) < heavy, F.lit(0)).otherwise(1 + F.pmod("id", F.lit(groups - 1)))
    return _around(spark.range(n).withColumn("g", g.cast("long")), sigma, dims, side, seed, scale, offset)


def _fixed(value: Column, scale: float | None) -> Column:
    return value if scale is None else F.floor(value * scale + 0.5).cast("double")


def _around(rows: DataFrame, sigma: float, dims: int, side: float, seed: int, scale: float | None, offset: str) -> DataFrame:
    center = [side * fast_uniform(seed, f"c{i}", F.col("g")) for i in range(dims)]
    shift = [_normal(seed, f"n{i}", F.col("id")) for i in range(dims)]
    if offset == "radial":  # a normal length in a random direction
        norm = F.sqrt(sum((s * s for s in shift[1:]), shift[0] * shift[0]))
        shift = [s / norm * F.abs(_normal(seed, "len", F.col("id"))) for s in shift]
    return rows.select("id", F.array(*[_fixed(c + sigma * s, scale) for c, s in zip(center, shift, strict=True)]).alias("coords"), "g")
