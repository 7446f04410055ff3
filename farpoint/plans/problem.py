"""The k-center instance: points (id, coords), how many centers, which metric."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farpoint.functions.distance import Metric, metric


@dataclass(frozen=True)
class KCenterProblem:
    """``points`` has ``id BIGINT`` (unique) and ``coords ARRAY<DOUBLE>`` of one length."""

    points: DataFrame
    k: int
    measure: str | Metric = "euclidean"

    @property
    def metric(self) -> Metric:
        return metric(self.measure)

    def is_trivial(self) -> bool:
        """n <= k: every point is a center and the radius is 0."""
        return self.points.select("id").limit(self.k + 1).count() <= self.k


def bad_points(points: DataFrame, id_col: str = "id") -> DataFrame:
    """Points with a null or NaN coordinate or a null id."""
    broken = F.exists("coords", lambda v: v.isNull() | F.isnan(v))
    return points.where(F.col(id_col).isNull() | F.col("coords").isNull() | F.coalesce(broken, F.lit(True)))


def validated(points: DataFrame, null_policy: str = "reject") -> DataFrame:
    """``reject`` raises and tells how many points are bad; ``drop`` leaves them out; ``impute_mean`` fills coordinates in."""
    if null_policy == "reject":
        if n := bad_points(points).count():
            raise ValueError(f"{n} points have a null id or a null or NaN coordinate")
        return points
    if null_policy == "drop":
        return points.where("id is not null and coords is not null").where(~F.exists("coords", lambda v: v.isNull() | F.isnan(v)))
    if null_policy != "impute_mean":
        raise ValueError(null_policy)
    points = points.where("id is not null and coords is not null")
    good = lambda v: F.when(~F.isnan(v), v)
    dims = points.select(F.max(F.size("coords"))).first()[0] or 0
    if not dims:
        return points
    means = points.agg(*[F.avg(good(F.col("coords")[i])).alias(f"m{i}") for i in range(dims)]).first()
    return points.withColumn("coords", F.array(*[F.coalesce(good(F.col("coords")[i]), F.lit(means[i])) for i in range(dims)]))


def distinct_points(points: DataFrame) -> DataFrame:
    """One point, that of the smallest id, for each place; the radius of any solution stays the same."""
    return points.groupBy("coords").agg(F.min("id").alias("id")).select("id", "coords")
