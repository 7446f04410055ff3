"""Farthest-first traversal: the sequential 2-approximation, in one task or distributed."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from farpoint.functions.distance import Metric, metric
from farpoint.functions.hashing import md5_number
from farpoint.operators import kernels
from farpoint.sources.staging import materialise, release

CENTERS = "rank int, id long, coords array<double>, key double"


def center_batch(ids: np.ndarray, x: np.ndarray, picks: np.ndarray, keys: np.ndarray) -> pa.RecordBatch:
    """rank, id, coords, key (the order key at which the point was chosen; null for the first)."""
    coords = pa.array([row.tolist() for row in x[picks]], pa.list_(pa.float64()))
    finite = np.isfinite(keys)
    return pa.RecordBatch.from_arrays(
        [pa.array(np.arange(1, len(picks) + 1), pa.int32()), pa.array(ids[picks], pa.int64()), coords, pa.array(np.where(finite, keys, 0.0), pa.float64(), mask=~finite)], names=["rank", "id", "coords", "key"]
    )


def gathered(batches: Iterator[pa.RecordBatch]) -> tuple[np.ndarray, np.ndarray]:
    """ids and coordinates of a task's rows, sorted by id."""
    ids, xs = [], []
    for b in batches:
        if b.num_rows:
            ids.append(b.column("id").to_numpy(zero_copy_only=False))
            xs.append(kernels.matrix(b.column("coords")))
    if not ids:
        return np.empty(0, np.int64), np.empty((0, 1))
    return kernels.by_id(np.concatenate(ids), np.concatenate(xs))


def _one_task(k: int, measure: str | Metric, target: float, seed: int | None, seed_rule: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, x = gathered(batches)
        first = 0
        if seed is not None and len(ids):
            at = int(np.searchsorted(ids, seed))
            first = at if at < len(ids) and ids[at] == seed else 0
        picks, keys, _ = kernels.farthest_first(x, k, first, target, measure)
        yield center_batch(ids, x, picks, keys)

    return run


def choose_seed(points: DataFrame, rule: str | int = "min_id", salt: int = 42, measure: str | Metric = "euclidean") -> int | None:
    """The id to start from: ``min_id``, ``hash_min``, ``farthest_from_mean``, or a given id."""
    if isinstance(rule, int):
        return rule
    if rule == "min_id":
        return None  # the kernels' own rule
    if rule == "hash_min":
        row = points.agg(F.min_by("id", F.struct(md5_number(salt, "seed", F.col("id").cast("string")).alias("h"), "id"))).first()
        return row[0]
    if rule == "farthest_from_mean":
        dims = len((points.select("coords").first() or [[]])[0])
        if not dims:
            return None
        mean = list(points.agg(*[F.avg(F.col("coords")[i]) for i in range(dims)]).first())
        return points.agg(F.max_by("id", F.struct(metric(measure).expr(F.col("coords"), mean).alias("d"), (-F.col("id")).alias("i")))).first()[0]
    raise ValueError(rule)


def farthest_first(points: DataFrame, k: int, measure: str | Metric = "euclidean", seed_rule: str | int = "min_id", target_key: float = 0.0, physical: str = "single_task") -> DataFrame:
    """Centers (rank, id, coords, key); ties go to the smallest id.

    ``single_task`` gathers the points, for sets that fit into one task (the sequential baseline).
    ``distributed`` gives the same centers from k scans and gathers nothing but one row each.
    """
    if physical == "distributed":
        return farthest_first_distributed(points, k, measure, seed_rule, target_key)
    if seed_rule == "worst_of":
        raise ValueError("worst_of is measured by baselines.worst_seed")
    seed = choose_seed(points, seed_rule, measure=measure)
    return points.select("id", "coords").repartition(1).mapInArrow(_one_task(k, measure, target_key, seed, str(seed_rule)), CENTERS)


def _key_to(point: Column, centers: list[list[float]], measure: str | Metric, before: Column | None = None) -> Column:
    parts = [metric(measure).expr(point, c) for c in centers]
    if before is not None:
        parts.insert(0, before)
    return F.least(*parts) if len(parts) > 1 else parts[0]


def farthest_first_distributed(points: DataFrame, k: int, measure: str | Metric = "euclidean", seed_rule: str | int = "min_id", target_key: float = 0.0, every: int = 8) -> DataFrame:
    """One job per center: each task lowers its points' keys and gives its farthest point.

    The lowered keys are written every ``every`` centers, so that an expression holds few centers and a
    lost executor costs the work since then.
    """
    spark = points.sparkSession
    state = points.select("id", "coords", F.lit(None).cast("double").alias("low"))
    seed = choose_seed(points, seed_rule, measure=measure)
    first = state.where(F.col("id") == seed) if seed is not None else state
    row = first.agg(F.min_by(F.struct("id", "coords"), "id").alias("p")).first()
    rows: list[tuple] = []
    kept, fresh = None, []
    if row and row.p:
        rows.append((1, row.p.id, list(row.p.coords), None))
        fresh.append(list(row.p.coords))
    while rows and len(rows) < k:
        low = _key_to(F.col("coords"), fresh, measure, F.col("low") if kept is not None else None)
        if len(fresh) > every:
            now = materialise(state.select("id", "coords", low.alias("low")), "lowered")
            if kept is not None:
                release(kept)
            state = kept = now
            fresh, low = [], F.col("low")
        top = state.select("id", "coords", low.alias("now")).agg(F.max_by(F.struct("id", "coords", "now"), F.struct("now", (-F.col("id")).alias("i"))).alias("p")).first().p
        if top.now <= target_key:
            break
        rows.append((len(rows) + 1, top.id, list(top.coords), float(top.now)))
        fresh.append(list(top.coords))
    if kept is not None:
        release(kept)
    return spark.createDataFrame(rows, CENTERS)


def radius_profile(centers: DataFrame, k: int) -> DataFrame:
    """k_prime, id, key: one run of k + 1 centers has the radius key for every smaller number of centers.

    The point that would be chosen next is the farthest one.
    """
    nxt = centers.select((F.col("rank") - 1).alias("k_prime"), F.col("key").alias("radius_key"))
    return centers.select(F.col("rank").alias("k_prime"), "id").join(nxt, "k_prime", "left").where(F.col("k_prime") <= k).select("k_prime", "id", F.coalesce("radius_key", F.lit(0.0)).alias("radius_key"))


def opt_lower_bound(points: DataFrame, k: int, measure: str | Metric = "euclidean") -> DataFrame:
    """lower_bound: half the distance at which a further center would be chosen is at most the optimum."""
    more = farthest_first(points, k + 1, measure).where(F.col("rank") == k + 1)
    return more.agg(F.coalesce(F.max(metric(measure).finish_expr(F.col("key"))) / 2, F.lit(0.0)).alias("lower_bound"))


def farthest_first_by_group(points: DataFrame, k: int, group: str, measure: str | Metric = "euclidean") -> DataFrame:
    """Centers of each group of ``group``: a k-center problem for every value; groups fit into a task."""

    def run(table: pa.Table) -> pa.Table:
        ids, x = gathered(table.to_batches())
        picks, keys, _ = kernels.farthest_first(x, k, 0, 0.0, measure)
        out = center_batch(ids, x, picks, keys)
        name = table.column(group)[0]
        return pa.table([pa.array([name.as_py()] * out.num_rows, name.type), *out.columns], names=[group, *out.schema.names])

    kind = dict(points.dtypes)[group]
    return points.select(group, "id", "coords").groupBy(group).applyInArrow(run, f"`{group}` {kind}, {CENTERS}")


def blocked_by_group(points: DataFrame, k: int, group: str, parts: int = 8, measure: str | Metric = "euclidean") -> DataFrame:
    """farthest_first_by_group for groups of any size: each group's parts first, then their centers (factor 4)."""

    def run(table: pa.Table) -> pa.Table:
        ids, x = gathered(table.to_batches())
        picks, _, _ = kernels.farthest_first(x, k, 0, 0.0, measure)
        name = table.column(group)[0]
        return pa.table([pa.array([name.as_py()] * len(picks), name.type), pa.array(ids[picks]), pa.array(x[picks].tolist(), pa.list_(pa.float64()))], names=[group, "id", "coords"])

    kind = dict(points.dtypes)[group]
    dealt = points.select(group, "id", "coords", F.pmod("id", F.lit(parts)).alias("part_no"))
    local = dealt.groupBy(group, "part_no").applyInArrow(run, f"`{group}` {kind}, id long, coords array<double>")
    return farthest_first_by_group(local, k, group, measure)


def farthest_first_edges(edges: DataFrame, k: int, seed: int | None = None) -> DataFrame:
    """Farthest-first on an explicit complete graph (u, v, w), both directions given: rank, id, key.

    Each step reads the edges of the newest center only.
    """
    spark = edges.sparkSession
    first = seed if seed is not None else edges.agg(F.min("u")).first()[0]
    if first is None:
        return spark.createDataFrame([], "rank int, id long, key double")
    chosen, rows = [first], [(1, first, None)]
    while len(rows) < k:
        low = edges.where(F.col("u").isin(chosen)).groupBy("v").agg(F.min("w").alias("w"))
        top = low.agg(F.max_by(F.struct("v", "w"), F.struct("w", (-F.col("v")).alias("i"))).alias("p")).first().p
        if top is None or top.w <= 0:
            break
        chosen.append(top.v)
        rows.append((len(rows) + 1, top.v, float(top.w)))
    return spark.createDataFrame(rows, "rank int, id long, key double")
