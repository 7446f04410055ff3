"""Pivot sampling: rounds of sampling with pruning around what was sampled, then a traversal.

While many points are live, some join the sample and a few become probes. The probe of a
given rank by distance to the sample is the pivot; live points no farther from the sample than it go.
The distance to the sample stays with each live point, so a round compares it with new members only.

An iteration reads the live points twice: draws depend on ids alone and give the table of new members; then the
points' keys are lowered and written. Probes are read off the written keys, the pruning is a filter of its next reading.
"""

from __future__ import annotations

import math
import time
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from farpoint.functions.distance import Metric
from farpoint.functions.hashing import fast_uniform, md5_below
from farpoint.operators import kernels
from farpoint.operators.blocked import blocked_farthest_first
from farpoint.operators.farthest_first import farthest_first
from farpoint.sources.staging import materialise, release

#: phi of the scheme as first published, and faster settings.
PRESET_ORIGINAL, PRESETS_FASTER = 8.0, (6.0, 4.0, 1.0)
#: New members sent to every task at once; more are sent in several passes.
BROADCAST_POINTS = 200_000
#: Rows that are put into boxes together, where there are many members.
BOXED_ROWS = 65_536


@dataclass(frozen=True)
class SamplingParams:
    n: int
    k: int
    eps: float = 0.1
    phi: float = PRESET_ORIGINAL
    log_base: float = math.e

    @property
    def log_n(self) -> float:
        return math.log(self.n) / math.log(self.log_base) if self.n > 1 else 0.0

    @property
    def threshold(self) -> float:
        """Sampling goes on while more points than this are live."""
        return (4 / self.eps) * self.k * self.n**self.eps * self.log_n

    def sample_rate(self, live: int) -> float:
        return min(1.0, 9 * self.k * self.n**self.eps * self.log_n / live)

    def probe_rate(self, live: int) -> float:
        return min(1.0, 4 * self.n**self.eps * self.log_n / live)

    @property
    def pivot_rank(self) -> int:
        return max(1, math.floor(self.phi * self.log_n))


@dataclass
class PivotSample:
    sample: DataFrame  # id, coords, part: "S" or "R"
    trace: list[dict]
    sampled: bool
    params: SamplingParams
    terminated: bool = True

    def rounds_as_published(self, machines: int = 50) -> DataFrame:
        """iteration, round_no, name, work: the three parallel rounds of each iteration as published, with the work of the slowest of
        ``machines``: draws in points, the pivot's and the pruning's in distances to the whole sample, as if nothing were kept."""
        rows, members, no = [], 0, 0
        for t in self.trace:
            share, members = -(-t["live"] // machines), members + t["new_sample"]
            for name, work in (("draw", share), ("pivot", t["probes"] * members), ("prune", share * members)):
                no += 1
                rows.append((t["iteration"], no, name, work))
        return self.sample.sparkSession.createDataFrame(rows, "iteration int, round_no int, name string, work long")

    def trace_frame(self) -> DataFrame:
        """iteration, live, new_sample, probes, pivot_key, live_after."""
        rows = [(t["iteration"], t["live"], t["new_sample"], t["probes"], t["pivot_key"], t["live_after"]) for t in self.trace]
        return self.sample.sparkSession.createDataFrame(rows, "iteration int, live long, new_sample long, probes long, pivot_key double, live_after long")


def _gathered(batches: Iterator[pa.RecordBatch], rows: int, share: int | None = None) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of ``rows``, cut after every ``share`` rows as well."""
    held, n, done = [], 0, 0
    for b in batches:
        while b.num_rows:
            most = min(rows, share - done % share) if share else rows
            held.append(b.slice(0, most - n))
            n += held[-1].num_rows
            b = b.slice(held[-1].num_rows)
            if n == most:
                yield from pa.Table.from_batches(held).combine_chunks().to_batches()
                held, n, done = [], 0, done + n
    if held:
        yield from pa.Table.from_batches(held).combine_chunks().to_batches()


def _lowered(members: "object", measure: str | Metric, share: int | None = None):
    """``share``: each so many rows of a task are the work of a machine, timed by itself."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        centers, spent, boxes, done = members.value, 0, None, 0
        many = kernels.boxed(centers, measure)
        for b in _gathered(batches, BOXED_ROWS, share) if many or share else batches:
            if share and done % share == 0:
                spent, boxes = 0, None
            done += b.num_rows
            if b.num_rows and len(centers):
                low = b.column("key").fill_null(np.inf).to_numpy(zero_copy_only=False)
                x = kernels.matrix(b.column("coords"))
                began = time.thread_time_ns()  # of the CPU: other tasks beside this one do not count
                if many:
                    boxes = boxes or kernels.Boxes(centers)
                    key = boxes.lower(x, low)
                else:
                    key = kernels.lower_keys(x, low, centers, measure)
                spent += time.thread_time_ns() - began
                new = {"key": pa.array(key), "ns": pa.array(np.full(len(key), spent))}
                b = pa.RecordBatch.from_arrays([new.get(n, c) for n, c in zip(b.schema.names, b.columns, strict=True)], schema=b.schema)
            yield b

    return run


def _draw(generator: str, seed: int, iteration: int, tag: str, rate: float) -> Column:
    """Whether a point is drawn at that rate."""
    if generator == "md5":
        return md5_below(rate, seed, iteration, tag, F.col("id").cast("string"))
    return fast_uniform(seed, iteration, tag, F.col("id")) < rate


def with_set_distance(points: DataFrame, members: np.ndarray, measure: str | Metric = "euclidean", share: int | None = None) -> DataFrame:
    """``points`` (id, coords, key, ...) with the key lowered by the rows of ``members``."""
    if "key" not in points.columns:
        points = points.withColumn("key", F.lit(None).cast("double"))
    for lo in range(0, len(members), BROADCAST_POINTS):
        sent = points.sparkSession.sparkContext.broadcast(members[lo : lo + BROADCAST_POINTS])
        points = points.mapInArrow(_lowered(sent, measure, share), points.schema)
    return points


def select_pivot(probes: np.ndarray, rank: int) -> float | None:
    """The key of the probe of that rank, farthest first; the nearest probe where there are fewer."""
    return float(np.sort(probes)[::-1][min(rank, len(probes)) - 1]) if len(probes) else None


def pivot_sample(
    points: DataFrame, k: int, eps: float = 0.1, phi: float = PRESET_ORIGINAL, seed: int = 42, tie_rule: str = "drop_equal", log_base: float = math.e, max_iterations: int = 100,
    measure: str | Metric = "euclidean", generator: str = "xxhash", n: int | None = None, machines: int | None = None,
) -> PivotSample:
    """The sample S and the points still live in the end, with a trace of the iterations.

    ``drop_equal`` also drops points exactly as far as the pivot, so sampled points always leave and
    the live set shrinks; ``keep_equal`` is the rule as first published and may stop at max_iterations.
    ``machines`` times the shares of the live points that so many machines would have, for simulated times (slowest_ns of a
    trace row). Shares are cut inside tasks; with no more tasks than machines one of them at least has a whole share.
    """
    points = points.select("id", "coords")
    n = points.count() if n is None else n
    params = SamplingParams(n, k, eps, phi, log_base)
    live, size, sample, trace = points.withColumn("key", F.lit(None).cast("double")), n, None, []
    kept, redraws = None, 0
    while size > params.threshold and len(trace) < max_iterations:
        iteration = len(trace) + 1
        new = materialise(live.where(_draw(generator, seed + redraws, iteration - 1, "S", params.sample_rate(size))).select("id", "coords"), "members")
        members = kernels.matrix(new.select("coords").toArrow().column(0).combine_chunks())  # about 9 k n^eps log n rows
        if not len(members) and sample is None:
            release(new)
            redraws += 1  # nothing drawn at first: distances to an empty sample are undefined
            continue
        sample = new if sample is None else sample.unionByName(new)
        drawn = live.withColumns({"in_h": _draw(generator, seed + redraws, iteration - 1, "H", params.probe_rate(size)), "ns": F.lit(0).cast("long")})
        share = -(-size // machines) if machines else None
        nearer = materialise(with_set_distance(drawn.coalesce(machines) if machines else drawn, members, measure, share), "live")
        probes = nearer.where("in_h").select("key").toArrow().column(0).to_numpy()  # about 4 n^eps log n rows
        pivot = select_pivot(probes, params.pivot_rank)
        limit = 0.0 if pivot is None else pivot
        stays = F.col("key") > limit if tie_rule == "drop_equal" else F.col("key") >= limit
        after, slowest = nearer.agg(F.count_if(stays), F.max("ns")).first()
        live = nearer.where(stays).select("id", "coords", "key")
        trace.append({"iteration": iteration, "live": size, "new_sample": len(members), "probes": len(probes), "pivot_key": limit, "live_after": after, "slowest_ns": slowest})
        if kept is not None:
            release(kept)
        kept, size = nearer, after
    rest = live.select("id", "coords", F.lit("R").alias("part"))
    if sample is None:
        return PivotSample(rest, trace, False, params)
    out = sample.select("id", "coords", F.lit("S").alias("part"))
    if tie_rule != "drop_equal":  # a sampled point may be live still, and be drawn again
        out = out.dropDuplicates(["id"])
        rest = rest.join(out.select("id"), "id", "left_anti").select("id", "coords", "part")
    out = out.unionByName(rest)
    return PivotSample(out, trace, True, params, size <= params.threshold)


def pivot_sampling_kcenter(points: DataFrame, k: int, final: str = "single_task", blocks: int = 8, measure: str | Metric = "euclidean", **options) -> tuple[DataFrame, PivotSample]:
    """Centers from the sample: by one traversal (factor 10), or ``blocked`` where it is too large (factor 18)."""
    drawn = pivot_sample(points, k, measure=measure, **options)
    if final == "blocked":
        return blocked_farthest_first(drawn.sample, k, blocks, measure=measure).centers, drawn
    return farthest_first(drawn.sample, k, measure), drawn


def max_sampling_k(n: int, eps: float = 0.1, log_base: float = math.e) -> int:
    """The largest k for which n points are sampled at all."""
    per_center = SamplingParams(n, 1, eps, log_base=log_base).threshold
    return max(0, math.ceil(n / per_center) - 1) if per_center else 0


def expected_trace(n: int, k: int, eps: float = 0.1, phi: float = PRESET_ORIGINAL, log_base: float = math.e, limit: int = 100) -> list[dict]:
    """Expected sizes by iteration: probes 4 n^eps log n, members 9 k n^eps log n, survivors phi / (4 n^eps)."""
    params, out, live = SamplingParams(n, k, eps, phi, log_base), [], float(n)
    while live > params.threshold and len(out) < limit:
        after = live * min(1.0, phi / (4 * n**eps))
        out.append({"iteration": len(out) + 1, "live": live, "new_sample": params.sample_rate(live) * live, "probes": params.probe_rate(live) * live, "live_after": after})
        if after >= live:
            break
        live = after
    return out

