"""Baselines and ablations: random centers, a plain random sample, the worst of several starts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farpoint.functions.hashing import md5_number, md5_uniform
from farpoint.operators.assign import covering_radius
from farpoint.operators.farthest_first import CENTERS, farthest_first


def random_centers(points: DataFrame, k: int, seed: int = 42) -> DataFrame:
    """The k points of the smallest hashes: the floor that any method has to beat."""
    h = md5_number(seed, "pick", F.col("id").cast("string"))
    top = points.select("id", "coords", h.alias("h")).orderBy("h", "id").limit(k)
    rows = [(i, r.id, list(r.coords), None) for i, r in enumerate(top.collect(), 1)]  # k rows
    return points.sparkSession.createDataFrame(rows, CENTERS)


def sample_then_traverse(points: DataFrame, k: int, rate: float, seed: int = 42) -> DataFrame:
    """A traversal over a uniform sample: what pivot sampling is without its pruning."""
    return farthest_first(points.where(md5_uniform(seed, "plain", F.col("id").cast("string")) < rate), k)


def worst_seed(points: DataFrame, k: int, seeds: list[int]) -> DataFrame:
    """seed, radius_key of the traversal from each start, the worst first."""
    out = None
    for s in seeds:
        row = covering_radius(points, farthest_first(points, k, seed_rule=s)).select(F.lit(s).cast("long").alias("seed"), "radius_key")
        out = row if out is None else out.unionByName(row)
    return out.orderBy(F.desc("radius_key"), "seed")
