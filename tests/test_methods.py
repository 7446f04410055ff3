import math

import numpy as np
import pytest

from farpoint.operators import assign as A
from farpoint.operators import baselines, exact, sampling
from farpoint.operators.blocked import blocked_farthest_first, local_round
from farpoint.operators.farthest_first import farthest_first, farthest_first_edges, opt_lower_bound, radius_profile
from farpoint.operators.partitioning import STRATEGIES, in_blocks, with_ranks
from farpoint.plans import bounds, cost, planner
from farpoint.plans.problem import KCenterProblem, bad_points, distinct_points, validated
from farpoint.sources import generators
from farpoint.sources.io import points_from_rows
from farpoint.sources.views import points_of


def ids_of(centers):
    return [r.id for r in centers.orderBy("rank").collect()]


def radius(points, centers):
    return A.covering_radius(points, centers).first().radius_key


def test_distributed_is_single_task(spark, sf):
    p = points_of(spark, sf, "orders_2d")
    a = farthest_first(p, 25).select("rank", "id", "key").collect()
    b = farthest_first(p.repartition(5), 25, physical="distributed").select("rank", "id", "key").collect()
    assert a == b
    tiny = points_from_rows(spark, [(3, [1.0]), (1, [1.0])])
    assert ids_of(farthest_first(tiny, 5, physical="distributed")) == [1] == ids_of(farthest_first(tiny, 5))
    empty = tiny.limit(0)
    assert ids_of(farthest_first(empty, 5)) == [] == ids_of(farthest_first(empty, 5, physical="distributed"))


def test_partitioning_does_not_matter(spark, sf):
    p = points_of(spark, sf, "events_2d")
    want = ids_of(farthest_first(p, 8))
    assert ids_of(farthest_first(p.repartition(7), 8)) == want
    assert ids_of(blocked_farthest_first(p, 8, 1).centers) == want
    assert ids_of(blocked_farthest_first(p.repartition(9), 8, 4).centers) == ids_of(blocked_farthest_first(p, 8, 4).centers)


def test_guarantees_against_the_optimum(spark):
    p = points_of(spark, "/root/testdata/sf0.01", "supplier_tiny")
    for k in (2, 3):
        few = p.where("id < 40") if k == 3 else p
        opt = exact.brute_force_opt(few, k).first().opt_key
        assert radius(few, farthest_first(few, k)) <= 4 * opt
        for strategy in STRATEGIES:
            assert radius(few, blocked_farthest_first(few, k, 4, strategy).centers) <= 16 * opt
        for rounds in (2, 3, 4):
            done = blocked_farthest_first(few, k, 8, rounds=rounds, n=few.count())
            assert done.plan.rounds == rounds and radius(few, done.centers) <= (2 * rounds) ** 2 * opt
        assert opt_lower_bound(few, k).first().lower_bound <= math.sqrt(opt)
        subset = few.where("id % 3 = 0")
        assert radius(subset, farthest_first(subset, k)) <= 4 * opt
        assert opt <= exact.opt_restricted(few, subset, k).first().opt_key


def test_tight_instance_of_two_rounds(spark):
    p = points_from_rows(spark, [(v, [float(v)]) for v in (1, 2, 3, 5, 6, 7)])
    block = p.selectExpr("id", "coords", "CASE WHEN id IN (2, 3) THEN 1 ELSE 0 END AS b").repartitionById(2, "b").select("id", "coords")
    done = blocked_farthest_first(block, 2, 2, "scan_split", level_seeds=[{0: 5, 1: 2}, {0: 3}])
    assert ids_of(done.centers) == [3, 1] and radius(p, done.centers) == 16
    assert exact.brute_force_opt(p, 2).first().opt_key == 1
    q = points_from_rows(spark, [(v, [float(v)]) for v in range(9)])
    block = q.selectExpr("id", "coords", "CASE WHEN id IN (2, 3) THEN 1 ELSE 0 END AS b").repartitionById(2, "b").select("id", "coords")
    done = blocked_farthest_first(block, 3, 2, "scan_split", level_seeds=[{0: 6, 1: 2}, {0: 4}])
    assert ids_of(done.centers) == [4, 0, 2] and radius(q, done.centers) == 16 and exact.brute_force_opt(q, 3).first().opt_key == 1


def test_blocks_are_whole_and_balanced(spark, sf):
    p = points_of(spark, sf, "orders_2d")
    for strategy in STRATEGIES:
        parts = in_blocks(p.select("id", "coords"), 8, strategy)
        rows = [(r[0], r[1]) for r in parts.selectExpr("spark_partition_id()", "id").collect()]
        assert sorted(i for _, i in rows) == list(range(1500))
        if strategy in ("ntile", "id_mod"):
            assert np.bincount([b for b, _ in rows]).max() == 188
    assert [r.rank0 for r in with_ranks(p).orderBy("id").collect()] == list(range(1500))


def test_levels_follow_from_the_capacity(spark, sf, monkeypatch):
    from farpoint.operators import blocked

    p = points_of(spark, sf, "orders_2d")
    done = blocked_farthest_first(p, 10, 16, capacity=100, keep_rounds=True)
    assert len(done.rounds) == 3 and done.plan.guarantee == 6
    assert [r.blocks for r in done.trace().orderBy("round_no").collect()] == [16, 2, 1]
    monkeypatch.setattr(blocked, "CAPACITY", 50)
    with pytest.raises(ValueError, match="capacity="):  # a further round is not added unasked
        blocked_farthest_first(p, 10, 16)


def test_chunks_bound_memory_and_keep_the_guarantee(spark, sf):
    p = points_of(spark, sf, "orders_2d")
    done = local_round(p, 5, 2, chunk=100)
    assert done.count() == 10 and {r.n_block for r in done.collect()} == {750}


def test_trace_counts(spark, sf):
    p = points_of(spark, sf, "orders_2d")
    done = blocked_farthest_first(p, 10, 8, keep_rounds=True)
    t = done.trace().orderBy("round_no").collect()
    want = cost.count_blocked([188] * 4 + [187] * 4, 10)
    assert [r.evaluations for r in t] == [want["round_1"], want["round_2"]] and sum(r.slowest_evaluations for r in t) == want["slowest"]
    assert all(r.slowest_ns > 0 for r in t)


def test_planner():
    plan = planner.plan_levels(5000, 10, 50, 100)
    assert [level.blocks for level in plan.levels] == [50, 5] and plan.rounds == 3 and plan.guarantee == 6 and plan.final_points == 50
    with pytest.raises(planner.CapacityStall):
        planner.block_counts(60, 4, 100)
    with pytest.raises(planner.CapacityStall):
        planner.plan_levels(400, 60, 4, 100)
    with pytest.raises(planner.CapacityStall):
        planner.plan_levels(1000, 5, 2, 100)
    assert planner.block_counts(10, 50, 100) == [50, 5, 1]
    for k in (1, 10, 30, 49):
        for m in (2, 17, 1000):
            for i, b in enumerate(planner.block_counts(k, m, 100)):
                assert i == 0 or b <= planner.machines_bound(m, k, 100, i) + 1e-9
    assert planner.plan_levels(7, 10, 4, 100).rounds == 1
    assert planner.feasibility(1000, 10, 10, 100)["two_rounds"] and planner.capacity_needed(1000, 10, 10) == 100
    assert planner.blocks_for(100, 30, 50) * 31 <= 100 + 31


def test_bounds():
    assert abs(bounds.phi_threshold(5, 1) - 3.93) < 0.01 and abs(bounds.phi_threshold(4, 1) - 5.08) < 0.01 and abs(bounds.phi_threshold(4, 1.05) - 5.34) < 0.01
    assert bounds.phi_holds(8) and bounds.phi_holds(4) and not bounds.phi_holds(1)
    assert round(cost.predict_slowdown(1_000_000)) == 98
    assert [sampling.max_sampling_k(n) for n in (6_000, 10_000, 15_000, 50_000, 60_000, 100_000, 1_000_000)] == [7, 10, 14, 39, 45, 68, 454]
    assert bounds.mapping_condition(10_000, 0.1) and not bounds.mapping_condition(1_000, 0.1)
    assert bounds.guarantee("pivot_sampling") == 10 and bounds.guarantee("pivot_sampling", alpha=4) == 18 and bounds.guarantee("blocked", 3) == 6


def test_sampling_invariants(spark):
    p = points_of(spark, "/root/testdata/sf0.01", "events_2d")
    for phi in (8, 1):
        one = sampling.pivot_sample(p, 5, phi=phi, generator="md5")
        assert one.sampled and one.terminated
        for a, b in zip(one.trace, one.trace[1:], strict=False):
            assert a["live_after"] == b["live"] < a["live"]
        counts = {r.part: r.n for r in one.sample.groupBy("part").agg({"id": "count"}).withColumnRenamed("count(id)", "n").collect()}
        assert counts["S"] == sum(t["new_sample"] for t in one.trace) and counts["R"] == one.trace[-1]["live_after"] <= one.params.threshold
        assert one.sample.select("id").distinct().count() == one.sample.count()
        assert radius(p, farthest_first(one.sample, 5)) <= 100 * radius(p, farthest_first(p, 5))
    again = sampling.pivot_sample(p.repartition(13), 5, phi=1, generator="md5")
    bare = lambda trace: [{k: v for k, v in t.items() if k != "slowest_ns"} for t in trace]
    assert bare(again.trace) == bare(one.trace) and all(t["slowest_ns"] > 0 for t in one.trace)
    fallback = sampling.pivot_sample(p, 50)
    assert not fallback.sampled and fallback.sample.count() == 10_000


def test_published_trace(spark):
    p = points_of(spark, "/root/testdata/sf0.01", "orders_2d")
    got = [(t["live"], t["new_sample"], t["probes"], t["live_after"]) for t in sampling.pivot_sample(p, 10, phi=8, generator="md5").trace]
    assert got == [(15000, 2283, 92, 12626), (12626, 2270, 102, 9381)]


def test_keep_equal_may_not_end(spark):
    rows = [(i, [0.0, 0.0]) for i in range(3000)]
    p = points_from_rows(spark, rows)
    assert sampling.pivot_sample(p, 1, phi=8, generator="md5").terminated
    stuck = sampling.pivot_sample(p, 1, phi=8, generator="md5", tie_rule="keep_equal", max_iterations=3)
    assert not stuck.terminated and len(stuck.trace) == 3 and stuck.sample.count() == 3000


def test_null_policies(spark):
    p = spark.createDataFrame([(1, [1.0, 2.0]), (2, [None, 4.0]), (3, [float("nan"), 0.0]), (None, [0.0, 0.0]), (5, None)], "id long, coords array<double>")
    assert bad_points(p).count() == 4
    with pytest.raises(ValueError, match="4 points"):
        validated(p)
    assert [r.id for r in validated(p, "drop").collect()] == [1]
    assert {r.id: list(r.coords) for r in validated(p, "impute_mean").collect()} == {1: [1.0, 2.0], 2: [1.0, 4.0], 3: [1.0, 0.0]}
    assert KCenterProblem(p, 5).is_trivial() and not KCenterProblem(p, 4).is_trivial()


def test_duplicates_edges_and_baselines(spark, sf):
    p = points_of(spark, sf, "part_2d")
    assert radius(p, farthest_first(distinct_points(p), 5)) == radius(p, farthest_first(p, 5))
    e = spark.createDataFrame([(a, b, float(abs(a - b))) for a in (0, 1, 5, 9, 10) for b in (0, 1, 5, 9, 10)], "u long, v long, w double")
    assert [r.id for r in farthest_first_edges(e, 3).orderBy("rank").collect()] == [0, 10, 5]
    assert exact.check_metric(e).first().asDict() == {"asymmetric": 0, "nonzero_self": 0, "negative": 0, "triangle": 0}
    broken = e.selectExpr("u", "v", "CASE WHEN u = 0 AND v = 10 THEN 99 ELSE w END AS w")
    assert exact.check_metric(broken).first().asymmetric == 2 and exact.check_metric(broken).first().triangle > 0
    assert radius(p, baselines.random_centers(p, 5)) >= radius(p, farthest_first(p, 5)) / 4
    worst = baselines.worst_seed(p, 3, [0, 5, 9]).collect()
    assert worst[0].radius_key == max(r.radius_key for r in worst)
    prof = radius_profile(farthest_first(p, 6), 5).orderBy("k_prime").collect()
    assert [r.radius_key for r in prof] == [radius(p, farthest_first(p, k)) for k in range(1, 6)]


def test_generators_and_recovery(spark):
    p = generators.gaussian_clusters(spark, 4000, 10, seed=2)
    assert p.repartition(3).exceptAll(p).count() == 0
    ten, nine = radius(p, farthest_first(p, 10)), radius(p, farthest_first(p, 9))
    assert ten < 2.0**2 and nine > 4 * ten
    s = generators.skewed_clusters(spark, 4000, 10)
    assert abs(s.where("g = 0").count() / 4000 - 0.5) < 0.05
    u = generators.uniform_square(spark, 2000)
    assert 0 <= u.selectExpr("min(coords[0])").first()[0] < u.selectExpr("max(coords[1])").first()[0] <= 100
    assert generators.gaussian_clusters(spark, 100, 5, offset="radial", scale=10_000).count() == 100


def test_assign_forms_agree(spark, sf):
    p = points_of(spark, sf, "orders_2d")
    c = farthest_first(p, 40)
    a = {r.id: (r.center_id, r.key) for r in A.assign(p, c).collect()}  # sent to the tasks
    assert a == {r.id: (r.center_id, r.key) for r in A.assign_join(p, c).collect()}
    few = c.where("rank <= 10")
    b = {r.id: (r.center_id, r.key) for r in A.assign(p, few).collect()}  # one expression
    assert b == {r.id: (r.center_id, r.key) for r in A.assign_join(p, few).collect()}
    assert all(a[r.id] == (r.id, 0.0) for r in c.collect())
    served = A.assign(p, few)
    assert A.cluster_profile(served).agg({"size": "sum"}).first()[0] == 1500
    assert A.within(served, 1e14).count() + A.outliers(served, 1e14).count() == 1500


def test_plans(spark, sf):
    from farpoint.plans.plan import make_plan, solve
    from farpoint.plans.problem import KCenterProblem

    assert make_plan(1000, 5, 8).algorithm == "farthest_first"
    big = make_plan(200_000_000_000, 100, 1000)
    assert big.algorithm == "blocked" and big.m == 100_000 and big.rounds == 3 and big.guarantee == 6 and "factor 6" in big.explain()
    with pytest.raises(planner.CapacityStall):
        make_plan(10_000_000, 5, 8, algorithm="farthest_first")
    assert make_plan(1_000_000, 10, 50, algorithm="pivot_sampling").warnings
    problem = KCenterProblem(points_of(spark, sf, "orders_2d"), 5)
    for algorithm in ("farthest_first", "distributed", "blocked", "pivot_sampling"):
        done = solve(problem, make_plan(1500, 5, 4, algorithm=algorithm))
        assert done.centers.count() == 5 and algorithm in done.explain()
