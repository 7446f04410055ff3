"""Optima by search with exact bounds, and checks of a metric given by its weights."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from farpoint.functions.distance import metric
from farpoint.operators import kernels

_keys = metric("euclidean").kernel


def _snapped(spots: np.ndarray, places: np.ndarray, k: int) -> float:
    """The key of some good set: farthest-first, then middles of the clusters, each snapped to a candidate."""
    picks, _, _ = kernels.farthest_first(spots, k)
    middles, best = spots[picks], np.inf
    for _ in range(8):
        chosen = np.array([places[int(np.argmin(_keys(places, c)))] for c in middles])
        which, low = kernels.nearest(spots, chosen)
        best = min(best, float(low.max()))
        middles = []
        for j in range(len(chosen)):
            own = spots[which == j]
            if len(own):
                at = own.mean(0)
                for step in range(1, 200):  # towards the middle of the smallest ball
                    at = at + (own[int(np.argmax(_keys(own, at)))] - at) / (step + 1)
                middles.append(at)
    return best


def improved(spots: np.ndarray, places: np.ndarray, low: np.ndarray, k: int, best: float) -> float:
    """The least key that ``k`` more of the places reach, or ``best`` where none is below it.

    The spot with the largest key needs a place nearer than the best key, so only those are tried; of the last
    place's candidates each spot that one of them leaves uncovered rules out all that are too far from it.
    """
    far = int(np.argmax(low))
    best = min(best, float(low[far]))
    if not k:
        return best
    near = places[_keys(places, spots[far]) < best]
    if k > 1:
        for c in near:
            best = improved(spots, places, np.minimum(low, _keys(spots, c)), k - 1, best)
        return best
    rest = low >= best
    while len(near):
        open_ = spots[rest]
        key = _keys(open_, near[0])
        w = int(np.argmax(key))
        if key[w] < best:
            best = float(np.minimum(low, _keys(spots, near[0])).max())
            rest = low >= best
            near = near[1:]
        else:
            near = near[_keys(near, open_[w]) < best]
    return best


def first_set(spots: np.ndarray, places: np.ndarray, low: np.ndarray, k: int, key: float, after: int) -> list[int] | None:
    """The first ``k`` rows of the places behind row ``after``, in their order, that cover all spots at ``key``."""
    far = int(np.argmax(low))
    if low[far] <= key:
        return list(range(after + 1, after + 1 + k)) if after + k < len(places) else None
    if not k:
        return None
    if k > 1:
        for c in range(after + 1, len(places) - k + 1):
            found = first_set(spots, places, np.minimum(low, _keys(spots, places[c])), k - 1, key, c)
            if found is not None:
                return [c, *found]
        return None
    open_ = spots[low > key]
    rows = after + 1 + np.flatnonzero(_keys(places[after + 1 :], spots[far]) <= key)
    while len(rows):
        d = _keys(open_, places[rows[0]])
        w = int(np.argmax(d))
        if d[w] <= key:
            return [int(rows[0])]
        rows = rows[_keys(places[rows], open_[w]) <= key]
    return None


def _searched(sent, k: int, key: float | None):
    """For rows of places (``i``): the least key with one of them, or, at a given key, the first set that begins with one of them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spots, places, best = sent.value
        found = None
        for b in batches:
            for i in b.column(0).to_pylist():
                low = _keys(spots, places[i])
                if key is None:
                    best = improved(spots, places, low, k - 1, best)
                elif found is None:
                    rest = first_set(spots, places, low, k - 1, key, i)
                    found = None if rest is None else [i, *rest]
        if key is None:
            yield pa.RecordBatch.from_arrays([pa.array([best])], names=["key"])
        elif found is not None:
            yield pa.RecordBatch.from_arrays([pa.array([found], pa.list_(pa.int64()))], names=["rows"])

    return run


def opt_restricted(points: DataFrame, candidates: DataFrame, k: int) -> DataFrame:
    """opt_key and the first optimal set (ids): the best k centers among ``candidates`` for ``points``.

    Points in one place are one spot; of candidates in one place the k smallest ids are enough for the first set. The first
    center is dealt over tasks, the others are searched with bounds that leave nothing out; time grows
    with spots times candidates for two centers, and may grow with the (k - 1)-th power of the candidates beyond.
    """
    spark = points.sparkSession
    spots = kernels.matrix(points.select("coords").distinct().toArrow().column(0).combine_chunks())
    place = Window.partitionBy("coords").orderBy("id")
    few = candidates.select("id", "coords").withColumn("r", F.row_number().over(place)).where(F.col("r") <= k).select("id", "coords").toArrow()
    if not len(spots) or few.num_rows < k or k < 1:
        return spark.createDataFrame([(None, None)], "opt_key double, ids array<bigint>")
    spots = spots[np.argsort(-_keys(spots, spots.mean(0)), kind="stable")]
    ids, places = kernels.by_id(few.column("id").to_numpy(), kernels.matrix(few.column("coords").combine_chunks()))
    best = _snapped(spots, places, k)
    sent = spark.sparkContext.broadcast((spots, places, best))
    tasks = 4 * spark.sparkContext.defaultParallelism
    near = [(int(i),) for i in np.flatnonzero(_keys(places, spots[0]) < best)]  # one center has to be nearer to the outermost spot
    if near:
        rows = spark.createDataFrame(near, "i long").repartition(tasks)
        best = min(best, rows.mapInArrow(_searched(sent, k, None), "key double").agg(F.min("key")).first()[0])
    rows = spark.range(0, len(places), 1, tasks)
    found = min(r.rows for r in rows.mapInArrow(_searched(sent, k, best), "rows array<long>").collect())
    return spark.createDataFrame([(best, [int(ids[i]) for i in found])], "opt_key double, ids array<bigint>")


def brute_force_opt(points: DataFrame, k: int) -> DataFrame:
    """The optimum over all points of the set itself."""
    return opt_restricted(points, points, k)


def check_metric(edges: DataFrame) -> DataFrame:
    """asymmetric, nonzero_self, negative, triangle: how many edges or triples (u, v, w) break the rule."""
    a, b = edges.alias("a"), edges.alias("b")
    back = edges.select(F.col("u").alias("v"), F.col("v").alias("u"), F.col("w").alias("w2"))
    asym = edges.join(back, ["u", "v"], "left").where(~F.col("w").eqNullSafe(F.col("w2"))).agg(F.count("*").alias("asymmetric"))
    two = a.join(b, F.col("a.v") == F.col("b.u")).select(F.col("a.u").alias("u"), F.col("b.v").alias("v"), (F.col("a.w") + F.col("b.w")).alias("way"))
    tri = edges.join(two, ["u", "v"]).where(F.col("w") > F.col("way") * (1 + 1e-12)).agg(F.count("*").alias("triangle"))
    rest = edges.agg(F.count_if((F.col("u") == F.col("v")) & (F.col("w") != 0)).alias("nonzero_self"), F.count_if(F.col("w") < 0).alias("negative"))
    return asym.crossJoin(rest).crossJoin(tri)
