"""Blocked farthest-first: a traversal in each block, then one over the blocks' centers."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farpoint.functions.distance import Metric
from farpoint.operators import kernels
from farpoint.operators.farthest_first import CENTERS, center_batch, gathered
from farpoint.operators.partitioning import in_blocks
from farpoint.plans.planner import Level, LevelPlan, blocks_for, plan_levels
from farpoint.sources.staging import materialise

LOCAL = "block int, " + CENTERS + ", n_block long, elapsed_ns long"
#: Points that one task solves, unless a capacity is given.
CAPACITY = 2_000_000
Solver = Callable[[np.ndarray, int, int, str], tuple[np.ndarray, np.ndarray, float]]


def default_solver(x: np.ndarray, k: int, seed: int, measure: str) -> tuple[np.ndarray, np.ndarray, float]:
    return kernels.farthest_first(x, k, seed, 0.0, measure)


def _block(k: int, measure: str | Metric, solver: Solver, seeds: dict[int, int], chunk: int | None):
    """``chunk`` bounds the rows of a block held at a time: where there are several, each leaves its k centers (one more round)."""

    def solved(ids, x, block):
        at = np.searchsorted(ids, seeds.get(block, ids[0])) if len(ids) else 0
        picks, keys, _ = solver(x, k, int(at) if at < len(ids) and ids[at] == seeds.get(block, ids[0]) else 0, measure)
        return picks, keys

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block, total, took = TaskContext.get().partitionId(), 0, 0
        if chunk is None:
            ids, x = gathered(batches)
            total = len(ids)
        else:
            kept_ids, kept_x, held, rows = [], [], [], 0

            def reduce():
                i, p = gathered(held)
                began = time.thread_time_ns()
                picks, _ = solved(i, p, block)
                kept_ids.append(i[picks])
                kept_x.append(p[picks])
                return time.thread_time_ns() - began

            for b in batches:
                held.append(b)
                rows += b.num_rows
                total += b.num_rows
                if rows >= chunk:
                    took += reduce()
                    held, rows = [], 0
            if kept_ids and rows:
                took += reduce()
            ids, x = kernels.by_id(np.concatenate(kept_ids), np.concatenate(kept_x)) if kept_ids else gathered(held)
        if not len(ids):
            return
        began = time.thread_time_ns()  # of the solver alone, on the CPU: moving the rows and other tasks are not counted
        picks, keys = solved(ids, x, block)
        took += time.thread_time_ns() - began
        out = center_batch(ids, x, picks, keys)
        n = out.num_rows
        extra = [pa.array([block] * n, pa.int32()), *out.columns, pa.array([total] * n, pa.int64()), pa.array([took] * n, pa.int64())]
        yield pa.RecordBatch.from_arrays(extra, names=["block", *out.schema.names, "n_block", "elapsed_ns"])

    return run


def local_round(points: DataFrame, k: int, m: int, strategy: str = "id_mod", measure: str | Metric = "euclidean", solver: Solver = default_solver, seeds: dict[int, int] | None = None, chunk: int | None = None) -> DataFrame:
    """Each block's centers; blocks are partitions, so nothing is shuffled beyond what the strategy asks for."""
    blocks = in_blocks(points.select("id", "coords"), m, strategy)
    return blocks.mapInArrow(_block(k, measure, solver, seeds or {}, chunk), LOCAL)


@dataclass
class BlockedResult:
    centers: DataFrame
    plan: LevelPlan
    rounds: list[DataFrame] = field(default_factory=list)

    def trace(self) -> DataFrame:
        """round_no, blocks, points, largest_block, out, evaluations, slowest_evaluations, slowest_ns."""
        return round_trace(self.rounds)


def round_trace(rounds: list[DataFrame]) -> DataFrame:
    out = None
    for no, done in enumerate(rounds, 1):
        per_block = done.groupBy("block").agg(F.count("*").alias("picked"), F.first("n_block").alias("n_block"), F.first("elapsed_ns").alias("elapsed_ns"))
        row = per_block.agg(
            F.lit(no).alias("round_no"), F.count("*").alias("blocks"), F.sum("n_block").alias("points"), F.max("n_block").alias("largest_block"), F.sum("picked").alias("centers"),
            F.sum(F.col("picked") * F.col("n_block")).alias("evaluations"), F.max(F.col("picked") * F.col("n_block")).alias("slowest_evaluations"), F.max("elapsed_ns").alias("slowest_ns"),
        )
        out = row if out is None else out.unionByName(row)
    return out


def blocked_farthest_first(
    points: DataFrame, k: int, m: int, strategy: str = "id_mod", measure: str | Metric = "euclidean", capacity: int | None = None, rounds: int | None = None, n: int | None = None,
    solver: Solver = default_solver, level_seeds: list[dict[int, int]] | None = None, keep_rounds: bool = False, chunk: int | None = None,
) -> BlockedResult:
    """Two rounds unless ``capacity`` (points of a task) or ``rounds`` asks for more; factor 2 * rounds. Centers of all blocks that
    do not fit into one task are an error without either, as further rounds cost quality.

    ``level_seeds`` gives a starting id for blocks of each level, the final one included as block 0.
    ``keep_rounds`` writes the rounds' centers for the trace, and so runs each block once.
    """
    if capacity is not None or rounds is not None:
        n = points.count() if n is None else n
        plan = plan_levels(n, k, m, capacity if capacity is not None else n, rounds)
        counts = [level.blocks for level in plan.levels]
    else:  # the size of the points is not asked for, only that all blocks' centers fit into one task
        counts = [points.rdd.getNumPartitions() if strategy == "scan_split" else m]
        if k * counts[0] > CAPACITY:
            raise ValueError(f"{counts[0]} blocks leave {k * counts[0]} centers, a task takes {CAPACITY}: give capacity= or rounds=, each further round adds 2 to the factor")
        plan = LevelPlan(tuple(Level(-1, b, k * b) for b in counts), k * counts[-1])
    level_seeds = level_seeds or []
    if strategy == "scan_split" and chunk is None:
        chunk = CAPACITY  # a split of the scan may have any number of points; a larger one counts as one more round
    at, done = points.select("id", "coords"), []
    for i, blocks in enumerate(counts):
        local = local_round(at, k, blocks, strategy if i == 0 or strategy not in ("scan_split", "range", "spatial_grid", "adversarial") else "id_mod", measure, solver, level_seeds[i] if i < len(level_seeds) else None, chunk if i == 0 else None)
        if keep_rounds or i + 1 < len(counts):
            local = materialise(local, "round")
        done.append(local)
        at = local.select("id", "coords")
    final = local_round(at, k, 1, "round_robin", measure, solver, level_seeds[len(counts)] if len(counts) < len(level_seeds) else None)
    if keep_rounds:
        final = materialise(final, "round")
    done.append(final)
    return BlockedResult(final.select("rank", "id", "coords", "key"), plan, done)


def slab_farthest_first(slabs: list[DataFrame], k: int, m: int, measure: str | Metric = "euclidean") -> DataFrame:
    """Data beyond what fits at once: the two-round scheme on each slab, then a traversal of all their centers."""
    union = None
    for slab in slabs:
        part = materialise(blocked_farthest_first(slab, k, m, measure=measure).centers, "slab").select("id", "coords")
        union = part if union is None else union.unionByName(part)
    return local_round(union, k, 1, "round_robin", measure).select("rank", "id", "coords", "key")


def auto_blocks(n: int, k: int, parallelism: int) -> int:
    """Blocks for n points: enough to use all tasks, never with fewer points than centers."""
    return blocks_for(n, k, parallelism)
