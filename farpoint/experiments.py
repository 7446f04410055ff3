"""The published experiment at its own sizes: ``python -m farpoint.experiments [FOLDER [MINUTES [RUNS]]]`` writes runs.json and tables.md.

Radius and slowest-machine time of the three methods for every k, three instances and two runs each; pivot
sampling for every k and pivot factor; times against the number of points. Instances differ in the
points' seed, runs in the seed of the draws (sampling) and in the first center (the others).
"""

from __future__ import annotations

import json
import os
import statistics
import sys
import time
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

from farpoint import workloads as W
from farpoint.operators.blocked import blocked_farthest_first, round_trace
from farpoint.operators.farthest_first import farthest_first
from farpoint.operators.sampling import pivot_sample
from farpoint.sources import generators
from farpoint.sources.staging import materialise, release

SCALE = 10_000
MACHINES = 50
INSTANCES, RUNS = (1, 2, 3), (1, 2)


def generated(spark: SparkSession, name: str, seed: int) -> DataFrame:
    """Points of a published set (fixed-point, so that keys are exact)."""
    kind, n, groups = name.split("_")
    if kind == "uniform":
        return generators.uniform_square(spark, int(n), seed=seed, scale=SCALE)
    make = generators.gaussian_clusters if kind == "clustered" else generators.skewed_clusters
    return make(spark, int(n), int(groups), seed=seed, scale=SCALE)


def measured(points: DataFrame, k: int, run: int, methods: tuple[str, ...], phi: float = 8.0) -> list[dict]:
    """method, radius, simulated seconds, wall seconds and iterations of one run of each method."""
    out, sets = [], []
    start = 0 if run == 1 else 1000 + run
    for method in methods:
        began, iterations = time.perf_counter(), None
        if method == "farthest_first":
            centers = farthest_first(points, k, seed_rule=start)
            coords = W.coords_of(centers)
            wall, ns = time.perf_counter() - began, W.solver_ns(points, k)
        elif method == "blocked":
            done = blocked_farthest_first(points, k, MACHINES, level_seeds=[{b: b + 350 * (run - 1) for b in range(MACHINES)}, {}], keep_rounds=True)
            coords = W.coords_of(done.centers)
            wall, ns = time.perf_counter() - began, sum(r.slowest_ns for r in round_trace(done.rounds).collect())
            for table in done.rounds:
                release(table)
        else:
            one = pivot_sample(points, k, phi=phi, seed=42 + run, machines=MACHINES)
            sample = materialise(one.sample, "sample")
            coords = W.coords_of(farthest_first(sample, k))
            wall, iterations = time.perf_counter() - began, len(one.trace)
            one.sample = sample
            ns = W.sampling_ns(one, k)
        sets.append(coords)
        out.append({"method": method, "k": k, "phi": phi if method == "pivot_sampling" else None, "run": run, "simulated": ns / 1e9, "wall": wall, "iterations": iterations})
    for row, key in zip(out, W.radii(points, sets), strict=True):
        row["radius"] = key**0.5 / SCALE
    return out


def experiment(spark: SparkSession, until: float, instances: tuple[int, ...] = INSTANCES, runs: tuple[int, ...] = RUNS) -> list[dict]:
    """All runs, the tables' sets first; stops to begin new sets at the time ``until``."""
    every = ("farthest_first", "blocked", "pivot_sampling")
    rows: list[dict] = []

    def over(name: str, ks: tuple[int, ...], phis: tuple[float, ...], methods: tuple[str, ...], table: str) -> None:
        for instance in instances:
            if time.time() > until:
                return
            points = materialise(generated(spark, name, instance).select("id", "coords"), "points")
            for k in ks:
                for run in runs:
                    for phi in phis:
                        rows.extend({"table": table, "set": name, "instance": instance, **r} for r in measured(points, k, run, methods if phi == phis[0] else ("pivot_sampling",), phi))
            release(points)
            print(f"{table} {name} instance {instance}: {len(rows)} runs", file=sys.stderr, flush=True)

    over("uniform_100000_0", W.KS, (8.0,), every, "uniform")
    over("unbalanced_200000_25", W.KS, (8.0,), every, "unbalanced")
    over("clustered_200000_25", W.KS, (8.0, 6.0, 4.0, 1.0), ("pivot_sampling",), "radius and time by phi")
    over("clustered_1000000_25", W.KS, (8.0,), every, "clustered")
    over("clustered_50000_50", W.KS, (8.0,), every, "clustered, 50 groups")
    for n in (10_000, 20_000, 50_000, 100_000, 200_000, 500_000):
        over(f"clustered_{n}_25", (10, 100), (8.0,), every, "time by n")
    over("clustered_1000000_50", W.KS, (8.0,), every, "clustered, 50 groups")
    return rows


def tables(rows: list[dict]) -> str:
    """Means over instances and runs, with the spread of the radius, as Markdown."""
    groups: dict[tuple, list[dict]] = {}
    for r in rows:
        groups.setdefault((r["table"], r["set"], r["k"], r["method"], r["phi"]), []).append(r)
    out, last = [], None
    for (table, name, k, method, phi), found in groups.items():
        if (table, name) != last:
            out += ["", f"**{table}: {name}**", "", "| k | method | runs | radius, mean | spread | slowest-machine s | wall s | iterations |", "| --- | --- | --- | --- | --- | --- | --- | --- |"]
            last = (table, name)
        radius = [r["radius"] for r in found]
        spread = statistics.stdev(radius) if len(radius) > 1 else 0.0
        told = f"{method} {phi:g}" if phi else method
        iterations = "" if found[0]["iterations"] is None else "-".join(str(x) for x in sorted({r["iterations"] for r in found}))
        out.append(f"| {k} | {told} | {len(found)} | {statistics.mean(radius):.4g} | {spread:.3g} | {statistics.mean(r['simulated'] for r in found):.4f} | {statistics.mean(r['wall'] for r in found):.2f} | {iterations} |")
    return "\n".join(out) + "\n"


def main() -> None:
    folder, minutes = Path(sys.argv[1] if len(sys.argv) > 1 else "."), float(sys.argv[2]) if len(sys.argv) > 2 else 600.0
    spark = SparkSession.builder.master(f"local[{os.environ.get('BENCH_CPUS', '8')}]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    rows = experiment(spark, time.time() + 60 * minutes, runs=RUNS[: int(sys.argv[3])] if len(sys.argv) > 3 else RUNS)
    (folder / "runs.json").write_text("[\n" + ",\n".join(json.dumps(r) for r in rows) + "\n]\n")
    (folder / "tables.md").write_text(tables(rows))


if __name__ == "__main__":
    main()
