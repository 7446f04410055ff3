"""The experiment workloads on the given tables and on generated ones.

One traversal answers all smaller numbers of centers, in every block as well, so a grid of k takes
one pass over the points for the traversals and one for the radii of all center sets.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable, Iterator
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from farpoint.operators import kernels
from farpoint.operators.blocked import blocked_farthest_first, local_round, round_trace
from farpoint.operators.farthest_first import CENTERS, center_batch, farthest_first, gathered
from farpoint.operators.sampling import PivotSample, pivot_sample
from farpoint.plans import cost
from farpoint.sources.staging import materialise
from farpoint.sources.views import points_of

KS = (2, 5, 10, 25, 50, 100)
PHIS = (1, 4, 6, 8)
EPSILONS = (0.05, 0.1, 0.2, 0.3)
#: Runs of a sweep at a time: while one waits for a small job others use the cores.
AT_ONCE = 6


def each(run: Callable, settings: Iterable[tuple]) -> list:
    """Results of ``run`` in the order of its settings, several at a time."""
    with ThreadPoolExecutor(AT_ONCE) as pool:
        return list(pool.map(lambda s: run(*s), settings))


def _final_for(ks: tuple[int, ...]):
    def run(table: pa.Table) -> pa.Table:
        k = table.column("k")[0].as_py()
        ids, x = gathered(table.select(["id", "coords"]).to_batches())
        picks, keys, _ = kernels.farthest_first(x, k)
        out = center_batch(ids, x, picks, keys)
        return pa.table([pa.array([k] * out.num_rows, pa.int32()), *out.columns], names=["k", *out.schema.names])

    return run


def blocked_grid(points: DataFrame, ks: tuple[int, ...], m: int, strategy: str = "id_mod") -> DataFrame:
    """k, rank, id, coords, key: two-round centers for each k from one pass over the blocks."""
    local = materialise(local_round(points, max(ks), m, strategy), "grid")
    dealt = local.select(F.explode(F.array(*[F.lit(k) for k in ks])).alias("k"), "rank", "id", "coords").where("rank <= k")
    return dealt.select("k", "id", "coords").groupBy("k").applyInArrow(_final_for(ks), "k int, " + CENTERS)


def _radii(sent):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sets = sent.value
        worst = np.zeros(len(sets))
        for b in batches:
            if b.num_rows:
                x = kernels.matrix(b.column("coords"))
                for i, centers in enumerate(sets):
                    worst[i] = max(worst[i], kernels.lower_keys(x, np.full(len(x), np.inf), centers).max())
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(sets)), pa.int32()), pa.array(worst)], names=["i", "radius_key"])

    return run


def radii(points: DataFrame, sets: list[np.ndarray]) -> list[float]:
    """The radius key of each center set, from one scan; each task gives a number for each set."""
    sent = points.sparkSession.sparkContext.broadcast(sets)
    rows = points.select("coords").mapInArrow(_radii(sent), "i int, radius_key double").groupBy("i").agg(F.max("radius_key").alias("r")).collect()
    return [r.r for r in sorted(rows)]


def coords_of(centers: DataFrame) -> np.ndarray:
    return np.array([list(r.coords) for r in centers.select("coords").collect()])


def radius_grid(points: DataFrame, dataset: str, ks: tuple[int, ...] = KS, m: int = 8, phis: tuple[float, ...] = (), **sampling) -> DataFrame:
    """dataset, k, alg, radius_key, radius, iterations for farthest-first, the blocked scheme and pivot sampling."""
    spark, labels, sets = points.sparkSession, [], []
    ff = farthest_first(points, max(ks)).orderBy("rank").collect()
    for k in ks:
        labels.append((dataset, k, "farthest_first", None))
        sets.append(np.array([list(r.coords) for r in ff[:k]]))
    grid: dict[int, list] = {}
    for r in blocked_grid(points, ks, m).collect():  # at most the sum of ks
        grid.setdefault(r.k, []).append(list(r.coords))
    for k in ks:
        labels.append((dataset, k, "blocked", None))
        sets.append(np.array(grid[k]))

    def drawn(phi: float, k: int) -> tuple:
        one = pivot_sample(points, k, phi=phi, n=n, **sampling)
        return (dataset, k, "pivot_sampling" if len(phis) == 1 else f"pivot_sampling_{phi:g}", len(one.trace)), coords_of(farthest_first(one.sample, k))

    n = points.count() if phis else None
    for label, centers in each(drawn, [(phi, k) for phi in phis for k in ks]):
        labels.append(label)
        sets.append(centers)
    rows = [(*label, r, float(np.sqrt(r))) for label, r in zip(labels, radii(points, sets), strict=True)]
    return spark.createDataFrame([(d, k, a, r, root, i) for d, k, a, i, r, root in rows], "dataset string, k int, alg string, radius_key double, radius double, iterations int")


def phi_sweep(points: DataFrame, ks: tuple[int, ...] = KS, phis: tuple[float, ...] = PHIS, **options) -> DataFrame:
    """k, phi, radius_key, iterations, sample_size, evaluations, sampled."""
    n = points.count()

    def drawn(k: int, phi: float) -> tuple:
        one = pivot_sample(points, k, phi=float(phi), n=n, **options)
        size = one.sample.count()
        counted = cost.count_sampling(one.trace, 50, size, k)
        return (k, float(phi), len(one.trace), size, sum(counted.values()), one.sampled), coords_of(farthest_first(one.sample, k))

    rows, sets = zip(*each(drawn, [(k, phi) for k in ks for phi in phis]), strict=True)
    out = [(k, phi, r, it, size, ev, s) for (k, phi, it, size, ev, s), r in zip(rows, radii(points, list(sets)), strict=True)]
    return points.sparkSession.createDataFrame(out, "k int, phi double, radius_key double, iterations int, sample_size long, evaluations long, sampled boolean")


def eps_sweep(points: DataFrame, k: int, epsilons: tuple[float, ...] = EPSILONS, **options) -> DataFrame:
    """eps, iterations, sample_size, radius_key."""
    n = points.count()

    def drawn(eps: float) -> tuple:
        one = pivot_sample(points, k, eps=eps, n=n, **options)
        return (eps, len(one.trace), one.sample.count()), coords_of(farthest_first(one.sample, k))

    rows, sets = zip(*each(drawn, [(eps,) for eps in epsilons]), strict=True)
    return points.sparkSession.createDataFrame([(*r, v) for r, v in zip(rows, radii(points, list(sets)), strict=True)], "eps double, iterations int, sample_size long, radius_key double")


def rounds_sweep(points: DataFrame, k: int, m: int, rounds: tuple[int, ...] = (2, 3, 4)) -> DataFrame:
    """rounds, guarantee, radius_key: what more rounds cost in quality."""
    n, rows, sets = points.count(), [], []
    for r in rounds:
        done = blocked_farthest_first(points, k, m, rounds=r, n=n)
        rows.append((done.plan.rounds, done.plan.guarantee))
        sets.append(coords_of(done.centers))
    return points.sparkSession.createDataFrame([(*r, v) for r, v in zip(rows, radii(points, sets), strict=True)], "rounds int, guarantee int, radius_key double")


def partitioner_sweep(points: DataFrame, k: int, m: int, strategies: tuple[str, ...] = ("id_mod", "hash", "random", "range", "ntile", "spatial_grid", "adversarial")) -> DataFrame:
    """strategy, radius_key."""
    sets = [coords_of(blocked_farthest_first(points, k, m, s).centers) for s in strategies]
    return points.sparkSession.createDataFrame(list(zip(strategies, radii(points, sets), strict=True)), "strategy string, radius_key double")


def tie_rule_sweep(points: DataFrame, k: int, limit: int = 6, **options) -> DataFrame:
    """tie_rule, iterations, terminated, still_live_members: members of the sample that stay live."""
    rows = []
    for rule in ("drop_equal", "keep_equal"):
        one = pivot_sample(points, k, tie_rule=rule, max_iterations=limit, **options)
        rows.append((rule, len(one.trace), one.terminated, one.trace[-1]["live_after"] if one.trace else 0))
    return points.sparkSession.createDataFrame(rows, "tie_rule string, iterations int, terminated boolean, live_after long")


def runtimes(points: DataFrame, dataset: str, ks: int | tuple[int, ...], m: int = 50, phi: float = 8.0, seed: int = 42) -> DataFrame:
    """dataset, alg, n, k, seconds (wall clock), simulated_seconds (the solvers on the slowest of m machines, summed over rounds), evaluations on the slowest machine, sampled.

    The points are taken to be materialised, so that reading them counts alike for all. Wall clock is taken of one run at a
    time, of sampling over the shares of m machines as of the blocked scheme over m blocks. Simulated times are CPU times inside
    the tasks of the same run; only the blocked rounds are run again, several at once, as keeping them would count as time.
    """
    ks, n, rows = (ks,) if isinstance(ks, int) else ks, points.count(), {}

    def rounds(k: int) -> tuple[int, int]:
        t = round_trace(blocked_farthest_first(points, k, m, keep_rounds=True).rounds).agg(F.sum("slowest_ns").alias("ns"), F.sum("slowest_evaluations").alias("e")).first()
        return t.ns or 0, t.e or 0

    for k in ks:
        began = time.perf_counter()
        ns = solver_ns(points, k)
        rows[k, "farthest_first"] = (time.perf_counter() - began, ns, cost.count_farthest_first(n, k), None)
        began = time.perf_counter()
        blocked_farthest_first(points, k, m).centers.collect()
        rows[k, "blocked"] = (time.perf_counter() - began,)
        began = time.perf_counter()
        one = pivot_sample(points, k, phi=phi, seed=seed, machines=m)
        ns = sum(t["slowest_ns"] for t in one.trace) + solver_ns(one.sample, k)
        took = time.perf_counter() - began
        size = sum(t["new_sample"] for t in one.trace) + (one.trace[-1]["live_after"] if one.trace else n)  # who is sampled is no longer live
        rows[k, f"pivot_sampling_{phi:g}"] = (took, ns, sum(cost.count_sampling(one.trace, m, size, k).values()), one.sampled)
    for k, (ns, e) in zip(ks, each(rounds, [(k,) for k in ks]), strict=True):
        rows[k, "blocked"] += (ns, e, None)
    out = [(dataset, alg, n, k, took, ns / 1e9, e, sampled) for (k, alg), (took, ns, e, sampled) in rows.items()]
    return points.sparkSession.createDataFrame(out, "dataset string, alg string, n long, k int, seconds double, simulated_seconds double, evaluations long, sampled boolean")


def sampling_ns(one: PivotSample, k: int) -> int:
    """The slowest machine of each iteration, where the sample was drawn with ``machines``, and the final traversal."""
    return sum(t["slowest_ns"] for t in one.trace) + solver_ns(one.sample, k)


def solver_ns(points: DataFrame, k: int) -> int:
    """Time of one traversal over all points in one task, without moving them; its centers come to the driver."""
    return max((r.elapsed_ns for r in local_round(points, k, 1, "round_robin").collect()), default=0)


def document_clusters(spark: SparkSession, sf_dir: str, k: int = 10) -> DataFrame:
    """center_id, size, radius_key, languages, quality_share of document clusters."""
    from farpoint.operators.assign import assign

    points = points_of(spark, sf_dir, "documents_tf")
    served = assign(points, farthest_first(points, k))
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select(F.col("doc_id").alias("id"), "lang")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select(F.col("doc_id").alias("id"), "quality")
    joined = served.join(docs, "id").join(labels, "id", "left")
    return joined.groupBy("center_id").agg(F.count("*").alias("size"), F.max("key").cast("bigint").alias("radius_key"), F.count_distinct("lang").alias("languages"), F.sum("quality").alias("n_quality"), F.count("quality").alias("n_labelled"))
