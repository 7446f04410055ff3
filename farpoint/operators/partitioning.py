"""Ways to deal points into blocks. Any is right for the guarantee; they differ in cost and balance."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from farpoint.functions.distance import metric
from farpoint.functions.hashing import fast_uniform, md5_number
from farpoint.sources.staging import materialise

STRATEGIES = ("scan_split", "round_robin", "id_mod", "hash", "random", "range", "ntile", "spatial_grid", "adversarial")


def in_blocks(points: DataFrame, m: int, strategy: str = "id_mod", seed: int = 42, axis: int = 0) -> DataFrame:
    """``points`` with one block in each partition.

    ``scan_split`` leaves the partitions of the scan as they are: no row moves. The others go by an
    explicit block number through repartitionById, as a hash of the number would join some blocks.
    """
    if strategy == "scan_split":
        return points
    if strategy == "round_robin":
        return points.repartition(m)
    if strategy == "ntile":
        ranked = with_ranks(points)
        n = ranked.count()
        small, extra = divmod(n, m)
        r = F.col("rank0")
        wide = F.lit(extra * (small + 1))
        block = F.when(r < wide, F.floor(r / (small + 1))).otherwise(extra + F.floor((r - wide) / max(small, 1)))
        return ranked.withColumn("block", block.cast("int")).drop("rank0").repartitionById(m, F.col("block")).drop("block")
    return points.repartitionById(m, block_of(points, m, strategy, seed, axis))


def block_of(points: DataFrame, m: int, strategy: str, seed: int = 42, axis: int = 0) -> Column:
    """The block number of a point, 0 to m - 1."""
    if strategy == "id_mod":
        return F.pmod("id", F.lit(m)).cast("int")
    if strategy == "hash":
        return F.pmod(md5_number(seed, "block", F.col("id").cast("string")), F.lit(m)).cast("int")
    if strategy == "random":
        return F.floor(fast_uniform(seed, F.col("id")) * m).cast("int")
    c = F.col("coords")
    if strategy == "range":  # equal widths of one coordinate; blocks may be uneven
        low, high = points.agg(F.min(c[axis]), F.max(c[axis])).first()
        return F.least(F.floor((c[axis] - low) * m / (high - low + 1)), F.lit(m - 1)).cast("int")
    if strategy == "spatial_grid":  # cells of a square grid over the first two coordinates
        side = max(1, int(m**0.5))
        low0, high0, low1, high1 = points.agg(F.min(c[0]), F.max(c[0]), F.min(c[1]), F.max(c[1])).first()
        cell = lambda i, lo, hi: F.least(F.floor((c[i] - lo) * side / (hi - lo + 1)), F.lit(side - 1))
        return (cell(0, low0, high0) * side + cell(1, low1, high1)).cast("int")
    if strategy == "adversarial":  # rings around the point of the smallest id: each block looks alike from inside
        first = points.agg(F.min_by("coords", "id")).first()[0]
        d = metric("euclidean").finish_expr(metric("euclidean").expr(c, list(first)))
        far = points.agg(F.max(d)).first()[0]
        return F.least(F.floor(d * m / (far + 1)), F.lit(m - 1)).cast("int")
    raise ValueError(strategy)


def with_ranks(points: DataFrame) -> DataFrame:
    """``points`` with rank0, the place of the id in order, from a range partitioning and its sizes."""
    ordered = points.repartitionByRange(F.col("id")).sortWithinPartitions("id")
    placed = materialise(ordered.withColumn("part", F.spark_partition_id()).withColumn("at", F.monotonically_increasing_id()), "ordered")
    sizes = placed.groupBy("part").agg(F.count("*").alias("n"), F.min("at").alias("first")).orderBy("part").collect()  # one row a partition
    ends = np.cumsum([r.n for r in sizes])
    offsets = pd.DataFrame({"part": [r.part for r in sizes], "offset": [int(e) - r.n - r.first for e, r in zip(ends, sizes, strict=True)]})
    small = points.sparkSession.createDataFrame(offsets, "part int, offset long") if len(offsets) else points.sparkSession.createDataFrame([], "part int, offset long")
    return placed.join(F.broadcast(small), "part").withColumn("rank0", F.col("at") + F.col("offset")).drop("part", "at", "offset")
