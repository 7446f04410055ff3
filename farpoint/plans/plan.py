"""From an instance to a plan to a result: which method, how many blocks and levels, at what predicted cost."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame

from farpoint.plans import bounds, cost
from farpoint.plans.planner import CapacityStall, blocks_for, plan_levels
from farpoint.plans.problem import KCenterProblem

ALGORITHMS = ("farthest_first", "distributed", "blocked", "pivot_sampling")


@dataclass(frozen=True)
class Plan:
    algorithm: str
    n: int
    k: int
    m: int
    capacity: int
    levels: tuple[int, ...]  # blocks of each level before the last round
    rounds: int
    guarantee: float
    evaluations: float  # predicted, on the slowest machine
    warnings: tuple[str, ...] = ()

    def explain(self) -> str:
        lines = [f"{self.algorithm}: n={self.n} k={self.k} m={self.m} capacity={self.capacity}", f"  levels {list(self.levels)}, {self.rounds} rounds, factor {self.guarantee:g}", f"  about {self.evaluations:.3g} distances on the slowest machine"]
        return "\n".join([*lines, *(f"  warning: {w}" for w in self.warnings)])


def make_plan(n: int, k: int, parallelism: int, capacity: int = 2_000_000, algorithm: str | None = None, eps: float = 0.1) -> Plan:
    """The cheapest method that fits: one task where the points fit and are few, else the blocked scheme."""
    if algorithm is not None and algorithm not in ALGORITHMS:
        raise ValueError(algorithm)
    if algorithm is None:
        algorithm = "farthest_first" if n <= capacity and k * n <= 10_000_000 else "blocked"
    warnings, m = [], blocks_for(n, k, max(parallelism, -(-n // capacity)))
    if algorithm == "farthest_first":
        if n > capacity:
            raise CapacityStall(f"{n} points do not fit into a task of {capacity}: distributed gives the same centers")
        return Plan(algorithm, n, k, 1, capacity, (), 1, bounds.guarantee(algorithm), cost.cost_farthest_first(n, k))
    if algorithm == "distributed":
        return Plan(algorithm, n, k, m, capacity, (), k, bounds.guarantee("farthest_first"), cost.cost_farthest_first(n, k) / m, (f"{k} passes over the points",))
    if algorithm == "blocked":
        levels = plan_levels(n, k, m, capacity)
        return Plan(algorithm, n, k, m, capacity, tuple(level.blocks for level in levels.levels), levels.rounds, levels.guarantee, cost.cost_blocked(n, k, m))
    evaluations = cost.cost_sampling(n, k, m, eps)
    slower = evaluations / cost.cost_blocked(n, k, m)
    if slower > 10:
        warnings.append(f"about {slower:.0f} times the distances of the blocked scheme")
    return Plan(algorithm, n, k, m, capacity, (), 0, bounds.guarantee(algorithm), evaluations, tuple(warnings))


@dataclass
class KCenterResult:
    centers: DataFrame
    plan: Plan
    trace: list[dict] = field(default_factory=list)
    rounds: list[DataFrame] = field(default_factory=list)

    def explain(self) -> str:
        return self.plan.explain() + "\n" + self.centers._jdf.queryExecution().explainString(self.centers._sc._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def solve(problem: KCenterProblem, plan: Plan, strategy: str = "scan_split", **options) -> KCenterResult:
    """Runs a plan on an instance."""
    from farpoint.operators.blocked import blocked_farthest_first
    from farpoint.operators.farthest_first import farthest_first
    from farpoint.operators.sampling import pivot_sampling_kcenter

    p, k, m = problem.points, problem.k, problem.measure
    if plan.algorithm == "blocked":
        points = p if strategy != "scan_split" or p.rdd.getNumPartitions() >= plan.m else p.repartition(plan.m)
        done = blocked_farthest_first(points, k, plan.m, strategy, m, **options)
        return KCenterResult(done.centers, plan, rounds=done.rounds)
    if plan.algorithm == "pivot_sampling":
        centers, drawn = pivot_sampling_kcenter(p, k, measure=m, **options)
        return KCenterResult(centers, plan, drawn.trace)
    return KCenterResult(farthest_first(p, k, m, physical="distributed" if plan.algorithm == "distributed" else "single_task", **options), plan)
