"""Assignment, covering radius and what is read off them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from farpoint.functions.distance import Metric, metric
from farpoint.operators import kernels

#: Center coordinates (k * dimensions) up to which distances are one expression inside the scan's stage.
LITERALS = 64
#: Centers sent to each task; more are joined in the plan.
BROADCAST_CENTERS = 200_000


def center_rows(centers: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    rows = sorted((r.id, list(r.coords)) for r in centers.select("id", "coords").limit(BROADCAST_CENTERS + 1).collect())
    if len(rows) > BROADCAST_CENTERS:
        raise ValueError(f"over {BROADCAST_CENTERS} centers: use assign_join")
    return np.array([r[0] for r in rows], np.int64), np.array([r[1] for r in rows])


def nearest_expr(coords: Column, ids: np.ndarray, x: np.ndarray, measure: str | Metric) -> Column:
    m = metric(measure)
    return F.least(*[F.struct(m.expr(coords, c.tolist()).cast("double").alias("key"), F.lit(int(i)).cast("long").alias("center_id")) for i, c in zip(ids, x, strict=True)]) if len(ids) > 1 else F.struct(m.expr(coords, x[0].tolist()).cast("double").alias("key"), F.lit(int(ids[0])).cast("long").alias("center_id"))


def _nearest(sent, measure: str | Metric):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, centers = sent.value
        for b in batches:
            if b.num_rows:
                x = kernels.matrix(b.column("coords"))
                which, key = kernels.nearest(x, centers, measure)
                yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(ids[which]), pa.array(key)], names=["id", "center_id", "key"])

    return run


def assign(points: DataFrame, centers: DataFrame, measure: str | Metric = "euclidean") -> DataFrame:
    """id, center_id, key: the nearest center of each point, of equals that of the smallest id."""
    ids, x = center_rows(centers)
    if not len(ids):
        raise ValueError("no centers")
    points = points.select("id", "coords")
    if x.size <= LITERALS:
        return points.select("id", nearest_expr(F.col("coords"), ids, x, measure).alias("n")).select("id", "n.center_id", "n.key")
    sent = points.sparkSession.sparkContext.broadcast((ids, x))
    return points.mapInArrow(_nearest(sent, measure), "id long, center_id long, key double")


def assign_join(points: DataFrame, centers: DataFrame) -> DataFrame:
    """assign() for squared Euclidean keys in the plan alone, for center sets too large to send to tasks.

    Grows with points times centers; partial minima keep one row for each point and task.
    """
    c = centers.select(F.col("id").alias("center_id"), F.col("coords").alias("c"))
    key = F.aggregate(F.zip_with("coords", "c", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)
    pairs = points.select("id", "coords").join(c).select("id", F.struct(key.alias("key"), "center_id").alias("n"))
    return pairs.groupBy("id").agg(F.min("n").alias("n")).select("id", "n.center_id", "n.key")


def covering_radius(points: DataFrame, centers: DataFrame, measure: str | Metric = "euclidean") -> DataFrame:
    """radius_key and radius: the largest distance of any point to its nearest center."""
    far = assign(points, centers, measure).agg(F.max("key").alias("radius_key"))
    return far.select("radius_key", metric(measure).finish_expr(F.col("radius_key")).alias("radius"))


def cluster_profile(assigned: DataFrame) -> DataFrame:
    """center_id, size, radius_key of each cluster."""
    return assigned.groupBy("center_id").agg(F.count("*").alias("size"), F.max("key").alias("radius_key"))


def within(assigned: DataFrame, key: float) -> DataFrame:
    """Points covered at that key."""
    return assigned.where(F.col("key") <= key)


def outliers(assigned: DataFrame, key: float) -> DataFrame:
    """Points left uncovered at that key."""
    return assigned.where(F.col("key") > key)


def farthest_points(assigned: DataFrame, t: int) -> DataFrame:
    """The t points farthest from their centers."""
    return assigned.orderBy(F.desc("key"), "id").limit(t)


def cost_sum(assigned: DataFrame, measure: str | Metric = "euclidean", power: int = 1) -> DataFrame:
    """Sum of distances to that power (1: k-median, 2: k-means), as a measure of a center set."""
    return assigned.agg(F.sum(F.pow(metric(measure).finish_expr(F.col("key")), F.lit(power))).alias("cost"))


def distance_quantiles(assigned: DataFrame, measure: str | Metric = "euclidean", at: tuple[float, ...] = (0.5, 0.9, 0.99)) -> DataFrame:
    d = metric(measure).finish_expr(F.col("key"))
    return assigned.agg(*[F.percentile_approx(d, q, 10_000).alias(f"p{round(q * 100)}") for q in at])


def satisfaction(points: DataFrame, sample: DataFrame, reference: DataFrame, measure: str | Metric = "euclidean") -> DataFrame:
    """id, center_id, key, sample_key, satisfied.

    A point is satisfied by the sample if some member is at least as near to the point's reference
    center as the point is.
    """
    served = assign(points, reference, measure)
    near = assign(reference, sample, measure).select(F.col("id").alias("center_id"), F.col("key").alias("sample_key"))
    return served.join(F.broadcast(near), "center_id").select("id", "center_id", "key", "sample_key", (F.col("sample_key") <= F.col("key")).alias("satisfied"))


def ball_join(points: DataFrame, centers: DataFrame, radius: float) -> DataFrame:
    """id, center_id, key of all pairs within ``radius``: cells of that side, then the exact distance."""
    cell = lambda v: F.floor(v / F.lit(float(radius))).cast("long")
    c = centers.select(F.col("id").alias("center_id"), F.col("coords").alias("c"))
    around = F.array(*[F.struct((cell(F.col("c")[0]) + i).alias("gx"), (cell(F.col("c")[1]) + j).alias("gy")) for i in (-1, 0, 1) for j in (-1, 0, 1)])
    c = c.select("center_id", "c", F.explode(around).alias("g")).select("center_id", "c", "g.gx", "g.gy")
    p = points.select("id", "coords", cell(F.col("coords")[0]).alias("gx"), cell(F.col("coords")[1]).alias("gy"))
    key = F.aggregate(F.zip_with("coords", "c", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)
    return p.join(c, ["gx", "gy"]).select("id", "center_id", key.alias("key")).where(F.col("key") <= radius * radius)


def farthest_per_cluster(assigned: DataFrame, t: int) -> DataFrame:
    """center_id, place, id, key: the t farthest points of each cluster.

    A cluster is first cut down in 64 parts, so that a large one is no large group.
    """
    w = Window.partitionBy("center_id").orderBy(F.desc("key"), "id")
    part = Window.partitionBy("center_id", "part").orderBy(F.desc("key"), "id")
    near = assigned.withColumn("part", F.pmod(F.xxhash64("id"), F.lit(64))).withColumn("r", F.row_number().over(part)).where(F.col("r") <= t)
    return near.withColumn("place", F.row_number().over(w)).where(F.col("place") <= t).select("center_id", "place", "id", "key")


def distance_profile(assigned: DataFrame, measure: str | Metric = "euclidean", bins: int = 20) -> DataFrame:
    """x, y: a histogram of the distances to the centers."""
    d = metric(measure).finish_expr(F.col("key").cast("double"))
    return assigned.agg(F.histogram_numeric(d, F.lit(bins)).alias("h")).select(F.explode("h").alias("b")).select("b.x", "b.y")


def nearest_center_udf(centers: DataFrame, measure: str | Metric = "euclidean"):
    """A scalar function coords -> id of the nearest center, for use in any expression."""
    ids, x = center_rows(centers)

    @F.arrow_udf("long")
    def nearest_center(coords: pa.Array) -> pa.Array:
        which, _ = kernels.nearest(kernels.matrix(coords), x, measure)
        return pa.array(ids[which])

    return nearest_center
