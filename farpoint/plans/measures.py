"""Measures over experiment runs: relative values, repeats, spread, the best of a row, simulated time."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from farpoint.sources.staging import materialise


def relative_value(runs: DataFrame, baseline: str = "farthest_first") -> DataFrame:
    """(dataset, k, alg, radius) with ``relative``: the radius over the baseline's."""
    base = runs.where(F.col("alg") == baseline).select(F.col("dataset").alias("b_dataset"), F.col("k").alias("b_k"), F.col("radius").alias("base_radius"))
    joined = runs.join(base, F.col("dataset").eqNullSafe(F.col("b_dataset")) & (F.col("k") == F.col("b_k")), "left").select("dataset", "k", "alg", "radius", "base_radius")
    return joined.withColumn("relative", F.when(F.col("base_radius") > 0, F.col("radius") / F.col("base_radius")))


def average_runs(runs: DataFrame, *keys: str, value: str = "radius") -> DataFrame:
    """mean, spread, least and most over repeats."""
    v = F.col(value)
    return runs.groupBy(*keys).agg(F.count("*").alias("repeats"), F.avg(v).alias("mean"), F.stddev_samp(v).alias("spread"), F.min(v).alias("least"), F.max(v).alias("most"))


def best_in_row(runs: DataFrame, row: str, column: str, value: str = "radius") -> DataFrame:
    """Marks with is_best the column of the least value of each row (the smallest column of equals)."""
    w = Window.partitionBy(row).orderBy(value, column)
    return runs.withColumn("is_best", F.row_number().over(w) == 1)


def result_table(runs: DataFrame, value: str = "radius") -> DataFrame:
    """A row for each dataset and k, a column for each algorithm."""
    return runs.groupBy("dataset", "k").pivot("alg", ["blocked", "pivot_sampling", "farthest_first"]).agg(F.first(value))


def rollup_runs(runs: DataFrame) -> DataFrame:
    """Means by dataset and algorithm with subtotals."""
    return runs.rollup("dataset", "alg").agg(F.count("*").alias("n_runs"), F.avg("radius").alias("mean_radius"))


def simulated_seconds(trace: DataFrame) -> DataFrame:
    """The slowest machine of each round, summed over rounds; data movement is not counted."""
    return trace.agg(F.sum(F.col("slowest_ns") / 1e9).alias("simulated_seconds"), F.sum("slowest_evaluations").alias("slowest_evaluations"))


def running_sample(trace: DataFrame) -> DataFrame:
    """Sampling trace with the sample's size so far and the live set's shrink ratio."""
    w = Window.orderBy("iteration")  # a trace has a row for each iteration
    return trace.withColumns({"sample_so_far": F.sum("new_sample").over(w.rowsBetween(Window.unboundedPreceding, 0)), "shrink": F.col("live_after") / F.col("live")})


def rank_in_live(live: DataFrame) -> DataFrame:
    """id, rank_live: how many live points are farther from the sample.

    The keys are ordered over all machines by ranges; each range needs only how many points the ranges before it have.
    """
    counts = live.groupBy("key").agg(F.count("*").alias("n"))
    ranges = materialise(counts.repartitionByRange(F.desc("key")).withColumn("part", F.spark_partition_id()), "ranges")
    sizes = sorted((r.part, r.n) for r in ranges.groupBy("part").agg(F.sum("n").alias("n")).collect())  # a row for each range
    before, offsets = 0, []
    for part, n in sizes:
        offsets.append((part, before))
        before += n
    small = F.broadcast(live.sparkSession.createDataFrame(offsets, "part int, offset long"))
    w = Window.partitionBy("part").orderBy(F.desc("key")).rowsBetween(Window.unboundedPreceding, -1)
    farther = ranges.join(small, "part").select("key", (F.col("offset") + F.coalesce(F.sum("n").over(w), F.lit(0))).alias("rank_live"))
    return live.join(farther, "key").select("id", "rank_live")


def low_rank_count(ranked: DataFrame, reference_ids: DataFrame, i: int) -> DataFrame:
    """low_ranked: how many reference points have rank at most i."""
    return ranked.join(reference_ids.select("id"), "id", "left_semi").agg(F.count_if(F.col("rank_live") <= i).alias("low_ranked"))


def cube_runs(runs: DataFrame) -> DataFrame:
    """Means by algorithm and k with all subtotals."""
    return runs.cube("alg", "k").agg(F.count("*").alias("n_runs"), F.avg("radius").alias("mean_radius"))


def grouping_sets_runs(runs: DataFrame) -> DataFrame:
    """Means by algorithm, and by k, in one table; which of them a row is stands in ``level``."""
    return runs.groupingSets([[F.col("alg")], [F.col("k")]], "alg", "k").agg(F.grouping_id().alias("level"), F.avg("radius").alias("mean_radius"))


def center_overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    """both, only_a, only_b: how many centers two methods share."""
    left, right = a.select("id"), b.select("id")
    both = left.intersect(right).agg(F.count("*").alias("both"))
    return both.crossJoin(left.exceptAll(right).agg(F.count("*").alias("only_a"))).crossJoin(right.exceptAll(left).agg(F.count("*").alias("only_b")))
