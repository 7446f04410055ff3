"""The registered queries of the k-center methods, with DuckDB SQL where SQL can tell them."""

from __future__ import annotations

import uuid
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from farpoint import oracles as O
from farpoint import workloads as W
from farpoint.operators import assign as A
from farpoint.operators import baselines, exact, sampling, threshold
from farpoint.operators.blocked import blocked_farthest_first, round_trace, slab_farthest_first
from farpoint.operators.farthest_first import blocked_by_group, farthest_first, farthest_first_by_group, farthest_first_edges, opt_lower_bound, radius_profile
from farpoint.plans import bounds, cost, measures, planner
from farpoint.plans.problem import distinct_points
from farpoint.sources import generators
from farpoint.sources.staging import materialise, shared_dir
from farpoint.sources.views import clustered_sql, points_of, stream_of

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def register(name: str, run: Query, sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        ORACLES[name] = sql


def picked(centers: DataFrame, kind: str = "bigint") -> DataFrame:
    return centers.select("rank", "id", F.coalesce(F.col("key"), F.lit(0.0)).cast(kind).alias("key"))  # 0 for the first center


# ---- farthest-first ----
for _name, _view, _k in (
    ("q_ff_orders_k10", "orders_2d", 10), ("q_ff_events_k5", "events_2d", 5), ("q_ff_customer_k25", "customer_2d", 25), ("q_ff_part_k5", "part_2d", 5),
    ("q_ff_lineitem4d_k25", "lineitem_4d", 25), ("q_ff_grid_k50", "lineitem_grid", 50), ("q_ff_embeddings_k10", "embeddings_64d", 10), ("q_ff_documents_k10", "documents_tf", 10),
    ("q_ff_gauss_k50", "gauss_on_orders", 50), ("q_ff_skew_k50", "skew_on_orders", 50), ("q_ff_region_trivial", "region_trivial", 10),
):
    register(_name, lambda s, d, v=_view, k=_k: picked(farthest_first(points_of(s, d, v), k)), O.farthest_first(_view, _k))

register("q_ff_distributed_orders_k10", lambda s, d: picked(farthest_first(points_of(s, d, "orders_2d"), 10, physical="distributed")), O.farthest_first("orders_2d", 10))
register("q_ff_seed_hash_orders", lambda s, d: picked(farthest_first(points_of(s, d, "orders_2d"), 10, seed_rule="hash_min")), O.farthest_first("orders_2d", 10, seed=O.duck_number("'42'", "'seed'", "CAST(id AS VARCHAR)") + ", id"))
register("q_ff_seed_given_orders", lambda s, d: picked(farthest_first(points_of(s, d, "orders_2d"), 10, seed_rule=777)), O.farthest_first("orders_2d", 10, seed="CAST(id <> 777 AS INT), id"))
register(
    "q_ff_seed_far_mean_customer", lambda s, d: picked(farthest_first(points_of(s, d, "customer_2d"), 5, seed_rule="farthest_from_mean")),
    O.farthest_first("customer_2d", 5, seed="-((c0 - (SELECT avg(c0) FROM pts)) * (c0 - (SELECT avg(c0) FROM pts)) + (c1 - (SELECT avg(c1) FROM pts)) * (c1 - (SELECT avg(c1) FROM pts))), id"),
)
register("q_ff_target_radius_orders", lambda s, d: picked(farthest_first(points_of(s, d, "orders_2d"), 100, target_key=1e14)), O.farthest_first("orders_2d", 100, final=O.PICKED.format("ff") + " WHERE rank = 1 OR key > 100000000000000"))
register(
    "q_ff_profile_orders", lambda s, d: radius_profile(farthest_first(points_of(s, d, "orders_2d"), 11), 10).select("k_prime", "id", F.col("radius_key").cast("bigint").alias("radius_key")),
    O.farthest_first("orders_2d", 11, final="SELECT * FROM (SELECT rank AS k_prime, id, CAST(lead(key) OVER (ORDER BY rank) AS BIGINT) AS radius_key FROM ff) WHERE k_prime <= 10"),
)
register("q_ff_lower_bound_orders", lambda s, d: opt_lower_bound(points_of(s, d, "orders_2d"), 10), O.farthest_first("orders_2d", 11, final="SELECT sqrt(CAST(key AS DOUBLE)) / 2 AS lower_bound FROM ff WHERE rank = 11"))
register("q_ff_dedupe_part_k5", lambda s, d: picked(farthest_first(distinct_points(points_of(s, d, "part_2d")), 5)), O.farthest_first("part_2d", 5))
for _metric, _key, _view, _kind in (("manhattan", O.manhattan, "orders_2d", "BIGINT"), ("chebyshev", O.chebyshev, "orders_2d", "BIGINT"), ("jaccard", O.jaccard, "documents_tf", "DOUBLE")):
    register(
        f"q_metric_{_metric}", lambda s, d, m=_metric, v=_view, t=_kind: picked(farthest_first(points_of(s, d, v), 8, m), t.lower()),
        O.farthest_first(_view, 8, key=_key, final=f"SELECT rank, id, coalesce(CAST(key AS {_kind}), 0) AS key FROM ff", kind=_kind),
    )


def _per_segment_sql() -> str:
    pts, dims = O.points_cte("customer_2d")
    return O.query([pts, *O.traversal("ff", "pts", dims, 5, "c_mktsegment")], "SELECT c_mktsegment, rank, id, coalesce(CAST(key AS BIGINT), 0) AS key FROM ff")


register("q_kcenter_per_segment", lambda s, d: farthest_first_by_group(points_of(s, d, "customer_2d"), 5, "c_mktsegment").select("c_mktsegment", "rank", "id", F.coalesce("key", F.lit(0.0)).cast("bigint").alias("key")), _per_segment_sql())


def _blocked_segment_sql() -> str:
    pts, dims = O.points_cte("customer_2d")
    ctes = [pts, "dealt AS MATERIALIZED (SELECT *, c_mktsegment || ':' || CAST(id % 4 AS VARCHAR) AS block FROM pts)", *O.traversal("level0", "dealt", dims, 5, "block")]
    ctes += [f"survivors AS MATERIALIZED (SELECT DISTINCT id, {O.cs(dims)}, split_part(block, ':', 1) AS c_mktsegment FROM level0)", *O.traversal("ff", "survivors", dims, 5, "c_mktsegment")]
    return O.query(ctes, "SELECT c_mktsegment, rank, id, coalesce(CAST(key AS BIGINT), 0) AS key FROM ff")


register("q_blocked_per_segment", lambda s, d: blocked_by_group(points_of(s, d, "customer_2d"), 5, "c_mktsegment", 4).select("c_mktsegment", "rank", "id", F.coalesce("key", F.lit(0.0)).cast("bigint").alias("key")), _blocked_segment_sql())


def nation_edges(s: SparkSession, d: str) -> DataFrame:
    p = points_of(s, d, "nation_tiny")
    a, b = p.select(F.col("id").alias("u"), F.col("coords").alias("a")), p.select(F.col("id").alias("v"), F.col("coords").alias("b"))
    w = F.aggregate(F.zip_with("a", "b", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda t, v: t + v)
    return a.crossJoin(b).select("u", "v", w.alias("w"))  # 25 x 25: the explicit matrix of the tiny set


register("q_edges_ff_nation", lambda s, d: picked(farthest_first_edges(nation_edges(s, d), 6)), O.farthest_first("nation_tiny", 6))
register(
    "q_check_metric_nation", lambda s, d: exact.check_metric(nation_edges(s, d).withColumn("w", F.sqrt("w"))),
    "SELECT CAST(0 AS BIGINT) AS asymmetric, CAST(0 AS BIGINT) AS nonzero_self, CAST(0 AS BIGINT) AS negative, CAST(0 AS BIGINT) AS triangle",
)

# ---- blocked farthest-first ----
for _name, _view, _k, _m in (("q_bff2_orders_k10_m8", "orders_2d", 10, 8), ("q_bff2_events_k10_m8", "events_2d", 10, 8), ("q_bff2_lineitem_k25_m50", "lineitem_4d", 25, 50), ("q_bff2_embeddings_k5_m4", "embeddings_64d", 5, 4), ("q_bff2_gauss_k25_m50", "gauss_on_orders", 25, 50)):
    register(_name, lambda s, d, v=_view, k=_k, m=_m: picked(blocked_farthest_first(points_of(s, d, v), k, m).centers), O.blocked(_view, _k, _m))
for _part in ("hash", "range", "ntile"):
    register(f"q_bff_{_part}_orders", lambda s, d, p=_part: picked(blocked_farthest_first(points_of(s, d, "orders_2d"), 10, 8, p).centers), O.blocked("orders_2d", 10, 8, _part))
# forced rounds halve the blocks: 50, 25, 12
register("q_bff3_lineitem_k10", lambda s, d: picked(blocked_farthest_first(points_of(s, d, "lineitem_4d"), 10, 50, rounds=3).centers), O.blocked("lineitem_4d", 10, 50, more=(25,)))
register("q_bff4_lineitem_k10", lambda s, d: picked(blocked_farthest_first(points_of(s, d, "lineitem_4d"), 10, 50, rounds=4).centers), O.blocked("lineitem_4d", 10, 50, more=(25, 12)))


def slabs(s: SparkSession, d: str) -> DataFrame:
    p = points_of(s, d, "orders_2d")
    return picked(slab_farthest_first([p.where(F.pmod("id", F.lit(3)) == i) for i in range(3)], 10, 4))


def _slab_sql() -> str:
    pts, dims = O.points_cte("orders_2d")
    ctes = [pts]
    for i in range(3):
        ctes += [f"dealt{i} AS MATERIALIZED (SELECT *, id % 4 AS block FROM pts WHERE id % 3 = {i})", *O.traversal(f"local{i}", f"dealt{i}", dims, 10, "block"), f"union{i} AS MATERIALIZED (SELECT DISTINCT id, c0, c1 FROM local{i})", *O.traversal(f"slab{i}", f"union{i}", dims, 10)]
    ctes += ["every AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT DISTINCT id, c0, c1 FROM slab{i}" for i in range(3)) + ")", *O.traversal("last", "every", dims, 10)]
    return O.query(ctes, O.PICKED.format("last"))


register("q_bff_slab_orders", slabs, _slab_sql())


def _tight(s: SparkSession, d: str) -> DataFrame:
    """Blocks and starts for which two rounds cost four times the optimum: centers, radius key and the optimum's. The points are the line numbers but 4."""
    numbers = s.read.parquet(f"{d}/lineitem.parquet").where("l_linenumber IN (1, 2, 3, 5, 6, 7)").select(F.col("l_linenumber").cast("long").alias("id")).distinct()
    p = numbers.select("id", F.array(F.col("id").cast("double")).alias("coords"))
    block = p.selectExpr("id", "coords", "CASE WHEN id IN (2, 3) THEN 1 ELSE 0 END AS b").repartitionById(2, "b").select("id", "coords")
    centers = blocked_farthest_first(block, 2, 2, "scan_split", level_seeds=[{0: 5, 1: 2}, {0: 3}]).centers
    found = A.covering_radius(p, centers).select(F.col("radius_key").cast("bigint").alias("radius_key"))
    return picked(centers).crossJoin(found).crossJoin(exact.brute_force_opt(p, 2).select(F.col("opt_key").cast("bigint").alias("opt_key")))


register("q_bff_tight_instance", _tight, O.query([
    "pts AS MATERIALIZED (SELECT DISTINCT CAST(l_linenumber AS BIGINT) AS id, CAST(l_linenumber AS BIGINT) AS c0, CAST(l_linenumber IN (2, 3) AS INT) AS block FROM lineitem WHERE l_linenumber IN (1, 2, 3, 5, 6, 7))",
    *O.traversal("local", "pts", 1, 2, "block", seed="CAST(id NOT IN (5, 2) AS INT), id"), "pooled AS MATERIALIZED (SELECT DISTINCT id, c0 FROM local)", *O.traversal("last", "pooled", 1, 2, seed="CAST(id <> 3 AS INT), id"),
    "pairs AS (SELECT a.id AS a, b.id AS b, max(least((p.c0 - a.c0) ** 2, (p.c0 - b.c0) ** 2)) AS w FROM pts p, pts a, pts b WHERE a.id < b.id GROUP BY 1, 2)"],
    f"SELECT rank, id, coalesce(CAST(key AS BIGINT), 0) AS key, CAST({O.radius_key('last', 1)} AS BIGINT) AS radius_key, (SELECT CAST(min(w) AS BIGINT) FROM pairs) AS opt_key FROM last"))
register("q_bff_scan_split_orders", lambda s, d: picked(blocked_farthest_first(points_of(s, d, "orders_2d"), 10, 8, "scan_split").centers))
register("q_bff_threshold_solver", lambda s, d: A.covering_radius(points_of(s, d, "customer_2d"), blocked_farthest_first(points_of(s, d, "customer_2d"), 5, 4, solver=threshold.threshold_solver).centers))

# ---- pivot sampling ----


def drawn(s: SparkSession, d: str, view: str, k: int, phi: float, **options) -> sampling.PivotSample:
    return sampling.pivot_sample(points_of(s, d, view), k, phi=phi, generator="md5", **options)


def traced(sample: sampling.PivotSample) -> DataFrame:
    return sample.trace_frame().withColumn("pivot_key", F.col("pivot_key").cast("bigint"))


for _name, _view, _k, _phi, _it in (("q_ps_sample_orders_phi4_k10", "orders_2d", 10, 4, 1), ("q_ps_sample_orders_phi1_k10", "orders_2d", 10, 1, 1), ("q_ps_sample_events_phi1_k5", "events_2d", 5, 1, 1)):
    register(_name, lambda s, d, v=_view, k=_k, p=_phi: drawn(s, d, v, k, p).sample.select("id", "part"), O.sampling(_view, _k, _phi, _it))
for _phi, _it in ((8, 2), (4, 1), (1, 1)):
    register(f"q_ps_kcenter_orders_phi{_phi}_k10", lambda s, d, p=_phi: picked(farthest_first(drawn(s, d, "orders_2d", 10, p).sample, 10)), O.sampling("orders_2d", 10, _phi, _it, O.PICKED.format("ff"), traverse=True))
    register(f"q_ps_trace_orders_phi{_phi}_k10", lambda s, d, p=_phi: traced(drawn(s, d, "orders_2d", 10, p)), O.sampling_trace("orders_2d", 10, _phi, _it))
register("q_ps_fallback_orders_k25", lambda s, d: picked(farthest_first(drawn(s, d, "orders_2d", 25, 8).sample, 25)), O.farthest_first("orders_2d", 25))
register("q_ps_keep_equal_grid", lambda s, d: traced(drawn(s, d, "lineitem_grid", 5, 4, tie_rule="keep_equal", max_iterations=1)), O.sampling_trace("lineitem_grid", 5, 4, 1, keep_equal=True))
register("q_ps_drop_equal_grid", lambda s, d: traced(drawn(s, d, "lineitem_grid", 5, 4, max_iterations=1)), O.sampling_trace("lineitem_grid", 5, 4, 1))
register("q_ps_final_blocked_orders", lambda s, d: picked(sampling.pivot_sampling_kcenter(points_of(s, d, "orders_2d"), 5, final="blocked", phi=4, generator="md5")[0]), O.query(
    [O.points_cte("orders_2d")[0], *O.sampling_ctes(2, 5, 4, 3, guarded=True), "dealt AS MATERIALIZED (SELECT id, c0, c1, id % 8 AS block FROM sample)", *O.traversal("level0", "dealt", 2, 5, "block"), "survivors AS MATERIALIZED (SELECT DISTINCT id, c0, c1 FROM level0)", *O.traversal("last", "survivors", 2, 5)],
    O.PICKED.format("last")))


def _rank_in_live(s: SparkSession, d: str) -> DataFrame:
    one = drawn(s, d, "orders_2d", 10, 4, max_iterations=1)
    rest = one.sample.where("part = 'R'").select("id", "coords")
    members = one.sample.where("part = 'S'")
    live = A.assign(rest, members).select("id", "key")
    return measures.rank_in_live(live).select("id", F.col("rank_live").cast("bigint").alias("rank_live"))


register("q_ps_pivot_rank", _rank_in_live, O.sampling("orders_2d", 10, 4, 1, "SELECT id, rank() OVER (ORDER BY d DESC) - 1 AS rank_live FROM live1"))



def _low_rank(s: SparkSession, d: str) -> DataFrame:
    """How many of the k centers of the whole set are among the i live points farthest from the sample."""
    ranked = materialise(_rank_in_live(s, d), "ranked")
    centers, out = farthest_first(points_of(s, d, "orders_2d"), 10), None
    for i in (0, 5, 50, 500, 5000):
        row = measures.low_rank_count(ranked, centers, i).select(F.lit(i).cast("long").alias("i"), "low_ranked")
        out = row if out is None else out.unionByName(row)
    return out


register("q_ps_low_rank_count", _low_rank, O.query([O.points_cte("orders_2d")[0], *O.sampling_ctes(2, 10, 4, 1), *O.traversal("ff", "pts", 2, 10), "ranked AS (SELECT id, rank() OVER (ORDER BY d DESC) - 1 AS rank_live FROM live1)"],
    "SELECT CAST(i AS BIGINT) AS i, (SELECT count(*) FROM ranked WHERE rank_live <= i AND id IN (SELECT id FROM ff)) AS low_ranked FROM (VALUES (0), (5), (50), (500), (5000)) AS t(i)"))
register("q_ps_rounds_as_published", lambda s, d: drawn(s, d, "orders_2d", 10, 8).rounds_as_published(50), O.sampled("orders_2d", 10, 8, " UNION ALL ".join(
    f"SELECT {i} AS iteration, {3 * i - 2 + j} AS round_no, '{name}' AS name, CAST({work} AS BIGINT) AS work FROM count{i}, go{i}, (SELECT {' + '.join(f'(SELECT count(*) FROM members{x})' for x in range(1, i + 1))} AS s) WHERE go"
    for i in range(1, 9) for j, (name, work) in enumerate((("draw", "ceil(m / 50.0)"), ("pivot", f"s * (SELECT count(*) FROM drawn{i} WHERE in_h)"), ("prune", "ceil(m / 50.0) * s")))), traverse=False))


def _slopes(s: SparkSession, d: str) -> DataFrame:
    """Of each kind of round: the slope of its work against k over runs that sample, and how well a line fits."""
    points, out = materialised(points_of(s, d, "orders_2d")), None
    for k in SLOPE_KS:
        rounds = sampling.pivot_sample(points, k, phi=8, generator="md5").rounds_as_published(50)
        row = rounds.groupBy("name").agg(F.sum("work").alias("work")).withColumn("k", F.lit(k))
        out = row if out is None else out.unionByName(row)
    return out.groupBy("name").agg(F.count("*").alias("runs"), F.round(F.regr_slope("work", "k"), 3).alias("slope"), F.round(F.regr_r2("work", "k"), 6).alias("fit"))


SLOPE_KS = (2, 4, 6, 8, 10, 12)
register("q_ps_round_slopes", _slopes, "SELECT name, count(*) AS runs, round(regr_slope(work, k), 3) AS slope, round(regr_r2(work, k), 6) AS fit FROM (" + O.all_of([O.sampled("orders_2d", _k, 8, f"SELECT {_k} AS k, name, sum(work) AS work FROM (" + " UNION ALL ".join(
    f"SELECT '{name}' AS name, CAST({work} AS BIGINT) AS work FROM count{i}, go{i}, (SELECT {' + '.join(f'(SELECT count(*) FROM members{x})' for x in range(1, i + 1))} AS s) WHERE go"
    for i in range(1, 9) for name, work in (("draw", "ceil(m / 50.0)"), ("pivot", f"s * (SELECT count(*) FROM drawn{i} WHERE in_h)"), ("prune", "ceil(m / 50.0) * s"))) + ") GROUP BY name", traverse=False) for _k in SLOPE_KS]) + ") GROUP BY name")

# ---- measures ----


def _with_centers(final: str, view: str = "orders_2d", k: int = 10) -> str:
    pts, dims = O.points_cte(view)
    return O.query([pts, *O.traversal("ff", "pts", dims, k), O.assigned_cte("ff", dims)], final)


def _served(s: SparkSession, d: str, view: str = "orders_2d", k: int = 10) -> DataFrame:
    p = points_of(s, d, view)
    return A.assign(p, farthest_first(p, k)).withColumn("key", F.col("key").cast("bigint"))


register("q_assign_orders", _served, _with_centers("SELECT id, n.center_id AS center_id, CAST(n.key AS BIGINT) AS key FROM assigned"))
register("q_assign_embeddings", lambda s, d: _served(s, d, "embeddings_64d", 10).select("id", "center_id"), _with_centers("SELECT id, n.center_id AS center_id FROM assigned", "embeddings_64d", 10))
register("q_assign_join_customer", lambda s, d: A.assign_join(points_of(s, d, "customer_2d"), farthest_first(points_of(s, d, "customer_2d"), 25)).withColumn("key", F.col("key").cast("bigint")), _with_centers("SELECT id, n.center_id AS center_id, CAST(n.key AS BIGINT) AS key FROM assigned", "customer_2d", 25))
register(
    "q_radius_orders", lambda s, d: A.covering_radius(points_of(s, d, "orders_2d"), farthest_first(points_of(s, d, "orders_2d"), 10)).withColumn("radius_key", F.col("radius_key").cast("bigint")),
    _with_centers("SELECT CAST(max(n.key) AS BIGINT) AS radius_key, sqrt(CAST(max(n.key) AS DOUBLE)) AS radius FROM assigned"),
)
register("q_cluster_profile_customer", lambda s, d: A.cluster_profile(_served(s, d, "customer_2d", 25)), _with_centers("SELECT n.center_id AS center_id, count(*) AS size, CAST(max(n.key) AS BIGINT) AS radius_key FROM assigned GROUP BY 1", "customer_2d", 25))
register("q_outliers_orders", lambda s, d: A.outliers(_served(s, d), 1e14), _with_centers("SELECT id, n.center_id AS center_id, CAST(n.key AS BIGINT) AS key FROM assigned WHERE n.key > 100000000000000"))
register("q_within_orders", lambda s, d: A.within(_served(s, d), 1e14).agg(F.count("*").alias("covered")), _with_centers("SELECT count(*) AS covered FROM assigned WHERE n.key <= 100000000000000"))
register("q_farthest_points_orders", lambda s, d: A.farthest_points(_served(s, d), 20), _with_centers("SELECT id, n.center_id AS center_id, CAST(n.key AS BIGINT) AS key FROM assigned ORDER BY n.key DESC, id LIMIT 20"))


def _cost(s: SparkSession, d: str) -> DataFrame:
    """The sum of squared distances: a BIGINT as in SQL, or DECIMAL(29, 0) where it is beyond (there the SQL's own cast fails)."""
    total = materialise(_served(s, d).agg(F.sum(F.col("key").cast("decimal(19,0)")).alias("cost")), "cost")
    return total.select(F.col("cost").cast("bigint")) if (total.first().cost or 0) < 1 << 63 else total


register("q_cost_sum_orders", _cost, _with_centers("SELECT CAST(sum(n.key) AS BIGINT) AS cost FROM assigned"))
register(
    "q_ball_join_orders", lambda s, d: A.ball_join(points_of(s, d, "orders_2d"), farthest_first(points_of(s, d, "orders_2d"), 10), 5_000_000.0).withColumn("key", F.col("key").cast("bigint")),
    _with_centers(f"SELECT p.id, c.id AS center_id, CAST({O.squared('p', 'c', 2)} AS BIGINT) AS key FROM pts p, ff c WHERE {O.squared('p', 'c', 2)} <= 25000000000000"),
)


def _satisfied(s: SparkSession, d: str) -> DataFrame:
    p = points_of(s, d, "orders_2d")
    sample = drawn(s, d, "orders_2d", 10, 4).sample.where("part = 'S'").select("id", "coords")
    return A.satisfaction(p, sample, farthest_first(p, 10)).groupBy("center_id").agg(F.count_if("satisfied").alias("n_satisfied"), F.count_if(~F.col("satisfied")).alias("n_unsatisfied"))


def _satisfied_sql(final: str) -> str:
    pts, dims = O.points_cte("orders_2d")
    ctes = [pts, *O.sampling_ctes(dims, 10, 4, 1), *O.traversal("ff", "pts", dims, 10), O.assigned_cte("ff", dims), f"reach AS (SELECT y.id, min({O.squared('y', 'm', dims)}) AS e FROM ff y, members1 m GROUP BY y.id)"]
    return O.query(ctes, final)


register("q_satisfaction_orders", _satisfied, _satisfied_sql("SELECT n.center_id AS center_id, count(*) FILTER (WHERE e <= n.key) AS n_satisfied, count(*) FILTER (WHERE e > n.key) AS n_unsatisfied FROM assigned a JOIN reach r ON r.id = a.n.center_id GROUP BY 1"))


def _unsatisfied(s: SparkSession, d: str) -> DataFrame:
    p = points_of(s, d, "orders_2d")
    one = drawn(s, d, "orders_2d", 10, 4)
    live = one.trace[0]["live"]
    found = A.satisfaction(p, one.sample.where("part = 'S'"), farthest_first(p, 10)).agg(F.count_if(~F.col("satisfied")).alias("unsatisfied"))
    return found.withColumn("bound", F.lit(bounds.unsatisfied_bound(live, one.params.n, 0.1))).select("unsatisfied", F.round("bound", 6).alias("bound"), (F.col("unsatisfied") < F.col("bound")).alias("holds"))


register("q_unsat_bound", _unsatisfied, _satisfied_sql("SELECT count(*) FILTER (WHERE e > n.key) AS unsatisfied, round(any_value(size.n / (3 * g)), 6) AS bound, count(*) FILTER (WHERE e > n.key) < any_value(size.n / (3 * g)) AS holds FROM assigned a JOIN reach r ON r.id = a.n.center_id, size").replace("count(*) FILTER (WHERE e > n.key)", "count(*) FILTER (WHERE e > a.n.key)"))


def _shrink(s: SparkSession, d: str) -> DataFrame:
    one = drawn(s, d, "orders_2d", 10, 8)
    lo, hi = bounds.shrink_bounds(1, one.params.n, 0.1)
    t = one.trace_frame()
    return t.select("iteration", F.round(F.col("live_after") / F.col("live"), 9).alias("shrink"), F.round(F.lit(lo), 9).alias("least"), F.round(F.lit(hi), 9).alias("most"), ((F.col("live_after") / F.col("live") >= lo) & (F.col("live_after") / F.col("live") <= hi)).alias("inside"))


register("q_shrink_check", _shrink, O.sampling("orders_2d", 10, 8, 2, " UNION ALL ".join(
    f"SELECT {i} AS iteration, round(b.m / CAST(a.m AS DOUBLE), 9) AS shrink, round(1 / g, 9) AS least, round(5 / g, 9) AS most, b.m / CAST(a.m AS DOUBLE) >= 1 / g AND b.m / CAST(a.m AS DOUBLE) <= 5 / g AS inside FROM count{i} a, (SELECT count(*) AS m FROM live{i}) b, size" for i in (1, 2))))


def _brute(s: SparkSession, d: str) -> DataFrame:
    return exact.brute_force_opt(points_of(s, d, "supplier_tiny"), 2).select(F.col("opt_key").cast("bigint").alias("opt_key"), F.col("ids")[0].alias("id_1"), F.col("ids")[1].alias("id_2"))


_pairs = f"worst AS (SELECT a.id AS id_1, b.id AS id_2, max(least({O.squared('p', 'a', 2)}, {O.squared('p', 'b', 2)})) AS opt_key FROM pts p, {{0}} a, {{0}} b WHERE a.id < b.id GROUP BY 1, 2)"
_brute_pts = O.points_cte("supplier_tiny")[0]
register("q_bruteforce_supplier_k2", _brute, O.query([_brute_pts, _pairs.format("pts")], "SELECT CAST(opt_key AS BIGINT) AS opt_key, id_1, id_2 FROM worst ORDER BY opt_key, id_1, id_2 LIMIT 1"))
register(
    "q_opt_restricted_supplier", lambda s, d: exact.opt_restricted(points_of(s, d, "supplier_tiny"), points_of(s, d, "supplier_tiny").where("id % 4 = 0"), 2).select(F.col("opt_key").cast("bigint").alias("opt_key"), F.col("ids")[0].alias("id_1"), F.col("ids")[1].alias("id_2")),
    O.query([_brute_pts, "few AS (SELECT * FROM pts WHERE id % 4 = 0)", _pairs.format("few")], "SELECT CAST(opt_key AS BIGINT) AS opt_key, id_1, id_2 FROM worst ORDER BY opt_key, id_1, id_2 LIMIT 1"),
)


def _ratio(s: SparkSession, d: str) -> DataFrame:
    p = points_of(s, d, "supplier_tiny")
    opt = exact.brute_force_opt(p, 2).select("opt_key")
    if opt.first().opt_key is None:  # fewer points than centers
        return s.createDataFrame([(None, None)], "ff_ratio double, bff_ratio double")
    ff = A.covering_radius(p, farthest_first(p, 2)).select(F.col("radius_key").alias("ff_key"))
    bff = A.covering_radius(p, blocked_farthest_first(p, 2, 4).centers).select(F.col("radius_key").alias("bff_key"))
    # where the optimum is 0 so are the radii, and SQL's 0 / 0 is NaN
    ratio = lambda key: F.when(F.col("opt_key") > 0, F.round(F.sqrt(F.col(key) / F.col("opt_key")), 9)).otherwise(F.lit(float("nan")))
    return opt.crossJoin(ff).crossJoin(bff).select(ratio("ff_key").alias("ff_ratio"), ratio("bff_key").alias("bff_ratio"))


register("q_ratio_supplier_k2", _ratio, O.query([_brute_pts, _pairs.format("pts"), *O.traversal("ff", "pts", 2, 2), *O.blocked_ctes(2, 2, 4)],
    f"SELECT round(sqrt({O.radius_key('ff', 2)} / CAST(min(opt_key) AS DOUBLE)), 9) AS ff_ratio, round(sqrt({O.radius_key('last', 2)} / CAST(min(opt_key) AS DOUBLE)), 9) AS bff_ratio FROM worst"))


def _threshold(s: SparkSession, d: str) -> DataFrame:
    p = points_of(s, d, "supplier_tiny")
    return A.covering_radius(p, threshold.threshold_cover(p, 5)).select(F.col("radius_key").cast("bigint").alias("radius_key"))


register("q_threshold_cover_supplier", _threshold)


def _threshold_nation(s: SparkSession, d: str) -> DataFrame:
    p = points_of(s, d, "nation_tiny")
    return A.covering_radius(p, threshold.threshold_cover(p, 4)).select(F.col("radius_key").cast("bigint").alias("radius_key"))


# every pairwise key in turn: its greedy cover by balls of twice the distance; the least that needs four balls or fewer
register("q_threshold_cover_nation", _threshold_nation, O.query([O.points_cte("nation_tiny")[0], f"keys AS MATERIALIZED (SELECT DISTINCT {O.squared('a', 'b', 2)} AS r FROM pts a, pts b)",
    f"g AS (SELECT r, 1 AS rank, [(SELECT min(id) FROM pts)] AS ids FROM keys UNION ALL SELECT g.r, g.rank + 1, list_append(g.ids, m.id) FROM g, LATERAL (SELECT min(p.id) AS id FROM pts p WHERE NOT EXISTS (SELECT 1 FROM pts c WHERE list_contains(g.ids, c.id) AND {O.squared('p', 'c', 2)} <= 4 * g.r)) m WHERE m.id IS NOT NULL AND g.rank < 6)",
    "best AS MATERIALIZED (SELECT arg_max(ids, rank) AS ids FROM g WHERE r = (SELECT min(r) FROM (SELECT r FROM g GROUP BY r HAVING max(rank) <= 4)))", "few AS MATERIALIZED (SELECT p.* FROM pts p, best WHERE list_contains(best.ids, p.id))"],
    f"SELECT CAST({O.radius_key('few', 2)} AS BIGINT) AS radius_key"))
_grid_points = O.points_cte("nation_tiny")[0]
register(
    "q_known_opt_cover_nation", lambda s, d: threshold.known_opt_cover(points_of(s, d, "nation_tiny"), 100.0).select("rank", "id"),
    O.query([_grid_points, f"g AS (SELECT 1 AS rank, min(id) AS id, [min(id)] AS ids FROM pts UNION ALL SELECT g.rank + 1, m.id, list_append(g.ids, m.id) FROM g, LATERAL (SELECT min(p.id) AS id FROM pts p WHERE NOT EXISTS (SELECT 1 FROM pts c WHERE list_contains(g.ids, c.id) AND {O.squared('p', 'c', 2)} <= 100)) m WHERE m.id IS NOT NULL)"], "SELECT rank, id FROM g"),
)


def _random(s: SparkSession, d: str) -> DataFrame:
    p = points_of(s, d, "orders_2d")
    return A.covering_radius(p, baselines.random_centers(p, 10)).select(F.col("radius_key").cast("bigint").alias("radius_key"))


_pts_orders = O.points_cte("orders_2d")[0]
register("q_random_centers_orders", _random, O.query([_pts_orders, f"few AS (SELECT * FROM pts ORDER BY {O.duck_number(repr('42'), repr('pick'), 'CAST(id AS VARCHAR)')}, id LIMIT 10)"], f"SELECT CAST({O.radius_key('few', 2)} AS BIGINT) AS radius_key"))
register(
    "q_sample_then_traverse_orders", lambda s, d: picked(baselines.sample_then_traverse(points_of(s, d, "orders_2d"), 10, 0.3)),
    O.query([_pts_orders, f"few AS MATERIALIZED (SELECT * FROM pts WHERE {O.duck_uniform(repr('42'), repr('plain'), 'CAST(id AS VARCHAR)')} < 0.3)", *O.traversal("ff", "few", 2, 10)], O.PICKED.format("ff")),
)

# ---- planning, cost and bounds (arithmetic on the sizes of groups of lines, and on stated grids) ----
_GRID = [(k, m, c) for k in (2, 10, 100) for m in (8, 50) for c in (2_000, 200_000)]
_LEVELS = [(10, 100), (40, 100), (49, 100), (7, 30)]
_SIZES_SQL = "(SELECT count(*) AS n FROM lineitem GROUP BY l_returnflag)"


def _values(s: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return s.createDataFrame(rows, schema)


def _told(rows: DataFrame, tell: Callable[..., list[tuple]], schema: str) -> DataFrame:
    """Rows that ``tell`` makes of each of a few rows, inside the plan."""

    def run(batches):
        for b in batches:
            out = [row for values in zip(*[c.to_pylist() for c in b.columns], strict=True) for row in tell(*values)]
            yield pa.RecordBatch.from_pylist([dict(zip(kinds.names, row, strict=True)) for row in out], schema=kinds)

    kinds = to_arrow_schema(StructType.fromDDL(schema))
    return rows.mapInArrow(run, schema)


def _sizes(s: SparkSession, d: str) -> DataFrame:
    """n: how many lines have each return flag."""
    return s.read.parquet(f"{d}/lineitem.parquet").groupBy("l_returnflag").agg(F.count("*").alias("n")).select("n")


def _sized(tell: Callable[..., list[tuple]], schema: str) -> Query:
    return lambda s, d: _told(_sizes(s, d), tell, schema)


def _grid_sql(columns: str = "k, m, c") -> str:
    return f"{_SIZES_SQL} AS g, (VALUES {', '.join(map(str, _GRID))}) AS t({columns})"


register(
    "q_feasibility", _sized(lambda n: [(n, k, m, c, planner.capacity_needed(n, k, m), *planner.feasibility(n, k, m, c).values()) for k, m, c in _GRID],
    "n long, k long, m long, c long, needed long, block_fits boolean, union_fits boolean, stored boolean, centers_fit boolean, two_rounds boolean"),
    f"SELECT CAST(n AS BIGINT) AS n, CAST(k AS BIGINT) AS k, CAST(m AS BIGINT) AS m, CAST(c AS BIGINT) AS c, CAST(greatest(ceil(n / m), k * m) AS BIGINT) AS needed, ceil(n / m) <= c AS block_fits, k * m <= c AS union_fits, m * c >= n AS stored, k <= c AS centers_fit, ceil(n / m) <= c AND k * m <= c AS two_rounds FROM {_grid_sql()}",
)


def _levels_sql() -> str:
    """k, m, c: as many blocks as hold the lines of a flag."""
    return f"(SELECT CAST(k AS BIGINT) AS k, CAST(ceil(n / CAST(c AS DOUBLE)) AS BIGINT) AS m, CAST(c AS BIGINT) AS c FROM {_SIZES_SQL} AS s, (VALUES {', '.join(map(str, _LEVELS))}) AS t(k, c))"


register("q_level_plan", _sized(lambda n: [(k, -(-n // c), c, i, b) for k, c in _LEVELS for i, b in enumerate(planner.block_counts(k, -(-n // c), c))], "k long, m long, c long, level long, blocks long"), f"""WITH RECURSIVE g AS {_levels_sql()},
r AS (SELECT k, m, c, CAST(0 AS BIGINT) AS level, m AS blocks FROM g UNION ALL SELECT k, m, c, level + 1, CAST(ceil(k * blocks / CAST(c AS DOUBLE)) AS BIGINT) FROM r WHERE blocks > 1) SELECT k, m, c, level, blocks FROM r""")
register(
    "q_machines_bound", _sized(lambda n: [(k, -(-n // c), c, i, round(planner.machines_bound(-(-n // c), k, c, i), 6)) for k, c in _LEVELS for i in range(1, 6)], "k long, m long, c long, i long, bound double"),
    f"SELECT k, m, c, CAST(i AS BIGINT) AS i, round(m * pow(k / CAST(c AS DOUBLE), i) + (1 - pow(k / CAST(c AS DOUBLE), i)) / (1 - k / CAST(c AS DOUBLE)), 6) AS bound FROM {_levels_sql()}, range(1, 6) AS r(i)",
)
register("q_balanced_m", _sized(lambda n: [(n, k, m, planner.balanced_m(n, k)) for k, m, c in _GRID if c == 2_000], "n long, k long, m long, best_m long"), f"SELECT CAST(n AS BIGINT) AS n, CAST(k AS BIGINT) AS k, CAST(m AS BIGINT) AS m, CAST(greatest(1, round(sqrt(n / k))) AS BIGINT) AS best_m FROM {_grid_sql()} WHERE c = 2000")
_THEORY = [("farthest_first", 2.0), ("blocked", 4.0), ("pivot_sampling", 10.0)]


def _theory(s: SparkSession, d: str) -> DataFrame:
    rows = [(n, k, a, bounds.guarantee(a), round(cost.predict_cost(a, n, k, 50), 3)) for n in (15_000, 60_000, 1_000_000) for k in (2, 10, 100) for a, _ in _THEORY]
    return _values(s, rows, "n long, k long, alg string, factor double, evaluations double")


register("q_theory_table", _theory, """SELECT CAST(n AS BIGINT) AS n, CAST(k AS BIGINT) AS k, alg, CAST(factor AS DOUBLE) AS factor, round(CASE alg WHEN 'farthest_first' THEN k * n WHEN 'blocked' THEN k * n / 50.0 + k * k * 50
ELSE k * pow(n, 1.1) * ln(n) / (50 * pow(1 - pow(n, -0.1), 2)) END, 3) AS evaluations FROM (VALUES (15000), (60000), (1000000)) AS a(n), (VALUES (2), (10), (100)) AS b(k), (VALUES ('farthest_first', 2), ('blocked', 4), ('pivot_sampling', 10)) AS c(alg, factor)""")
register("q_slowdown", lambda s, d: _values(s, [(n, round(cost.predict_slowdown(n), 9)) for n in (10_000, 100_000, 1_000_000)], "n long, slowdown double"), "SELECT CAST(n AS BIGINT) AS n, round(pow(n, 0.1) * pow(1 - pow(n, -0.1), -2) * ln(n), 9) AS slowdown FROM (VALUES (10000), (100000), (1000000)) AS t(n)")
register("q_max_sampling_k", _sized(lambda n: [(n, sampling.max_sampling_k(n))], "n long, most_k long"), f"SELECT CAST(n AS BIGINT) AS n, CAST(greatest(0, ceil(n / (40 * pow(n, 0.1) * ln(n))) - 1) AS BIGINT) AS most_k FROM {_SIZES_SQL}")


def _factors(s: SparkSession, d: str) -> DataFrame:
    """p, x: the line numbers with the tax factors (1.00 to 1.08) that lines of that number have."""
    return s.read.parquet(f"{d}/lineitem.parquet").select(F.col("l_linenumber").cast("double").alias("p"), F.expr("(floor(l_tax * 100 + 0.5) + 100) / 100.0D").alias("x")).distinct()


_FACTORS_SQL = "(SELECT DISTINCT CAST(l_linenumber AS DOUBLE) AS p, (floor(l_tax * 100 + 0.5) + 100) / CAST(100 AS DOUBLE) AS x FROM lineitem)"
register("q_phi_threshold", lambda s, d: _told(_factors(s, d).where("p IN (4, 5)"), lambda b, x: [(b, x, round(bounds.phi_threshold(b, x), 6))], "b double, x double, phi double"), f"""WITH RECURSIVE g AS (SELECT p AS b, x FROM {_FACTORS_SQL} WHERE p IN (4, 5)),
r AS (SELECT b, x, x AS lo, CAST(1e6 AS DOUBLE) AS hi, 0 AS i FROM g UNION ALL SELECT b, x, CASE WHEN ok THEN lo ELSE mid END, CASE WHEN ok THEN mid ELSE hi END, i + 1
FROM (SELECT *, b * (mid + x / 2 - sqrt(2 * x * mid + x * x / 4)) >= mid + x + sqrt(2 * x * mid + x * x) AS ok FROM (SELECT *, (lo + hi) / 2 AS mid FROM r)) WHERE i < 200)
SELECT b, x, round(hi, 6) AS phi FROM r WHERE i = 200""")
register("q_feasible_roots", lambda s, d: _told(_factors(s, d), lambda phi, x: [(phi, x, round(bounds.feasible_acd(phi, x), 9), round(bounds.feasible_bcd(phi, x), 9))], "phi double, x double, acd double, bcd double"),
    f"SELECT p AS phi, x, round(p + x / 2 - sqrt(2 * x * p + x * x / 4), 9) AS acd, round(p + x + sqrt(2 * x * p + x * x), 9) AS bcd FROM {_FACTORS_SQL}")
register("q_rounds", lambda s, d: _values(s, [(a, i, cost.rounds(a, i, i)) for a, _ in _THEORY for i in (0, 1, 2, 3)], "alg string, i long, rounds long"),
    "SELECT alg, CAST(i AS BIGINT) AS i, CAST(CASE alg WHEN 'farthest_first' THEN 1 WHEN 'blocked' THEN i + 1 ELSE 3 * i + 1 END AS BIGINT) AS rounds FROM (VALUES ('farthest_first'), ('blocked'), ('pivot_sampling')) AS a(alg), range(0, 4) AS r(i)")
_EXPECTED = [(k, phi) for k in (2, 10, 100) for phi in (1.0, 8.0)]
_PARTS = ("live", "new_sample", "probes", "live_after")


def _expected(n: int) -> list[tuple]:
    return [(n, k, phi, t["iteration"], *(round(float(t[c]), 3) for c in _PARTS)) for k, phi in _EXPECTED for t in sampling.expected_trace(n, k, phi=phi)]


register("q_ps_expected_trace", _sized(_expected, "n long, k long, phi double, iteration long, " + ", ".join(f"{c} double" for c in _PARTS)), f"""WITH RECURSIVE g AS (SELECT CAST(n AS BIGINT) AS n, CAST(k AS BIGINT) AS k, CAST(phi AS DOUBLE) AS phi, pow(n, 0.1) AS w, ln(n) AS l FROM {_SIZES_SQL} AS s, (VALUES {', '.join(map(str, _EXPECTED))}) AS t(k, phi)),
r AS (SELECT *, CAST(1 AS BIGINT) AS iteration, CAST(n AS DOUBLE) AS live FROM g UNION ALL SELECT n, k, phi, w, l, iteration + 1, live * least(1, phi / (4 * w)) FROM r WHERE live * least(1, phi / (4 * w)) < live AND live > 40 * k * w * l)
SELECT n, k, phi, iteration, round(live, 3) AS live, round(least(live, 9 * k * w * l), 3) AS new_sample, round(least(live, 4 * w * l), 3) AS probes, round(live * least(1, phi / (4 * w)), 3) AS live_after FROM r WHERE live > 40 * k * w * l""")
register(
    "q_success_probability", lambda s, d: _values(s, [(n, round(bounds.success_probability(n, bounds.gamma_of(n)), 12), bounds.mapping_condition(n, 0.1)) for n in (1_000, 10_000, 1_000_000)], "n long, probability double, maps boolean"),
    "SELECT CAST(n AS BIGINT) AS n, round(1 - 2 * pow(n, -(1 + ln(ln(n)) / ln(n))), 12) AS probability, 5 / pow(n, 0.1) < 2 AS maps FROM (VALUES (1000), (10000), (1000000)) AS t(n)",
)


def _count_ff(s: SparkSession, d: str) -> DataFrame:
    return points_of(s, d, "orders_2d").agg(F.count("*").alias("n")).select("n", (F.col("n") * 10).alias("evaluations"))


register("q_distance_count_ff", _count_ff, "SELECT count(*) AS n, count(*) * 10 AS evaluations FROM orders")


def _count_bff(s: SparkSession, d: str) -> DataFrame:
    t = round_trace(blocked_farthest_first(points_of(s, d, "orders_2d"), 10, 8, keep_rounds=True).rounds)
    return t.select("round_no", "blocks", "points", "largest_block", "centers", "evaluations", "slowest_evaluations")


register("q_distance_count_bff", _count_bff, O.blocked("orders_2d", 10, 8, final="""
SELECT 1 AS round_no, count(*) AS blocks, CAST(sum(n) AS BIGINT) AS points, max(n) AS largest_block, CAST(sum(c) AS BIGINT) AS centers, CAST(sum(n * c) AS BIGINT) AS evaluations, max(n * c) AS slowest_evaluations
FROM (SELECT block, count(*) AS n FROM dealt GROUP BY block) JOIN (SELECT block, count(*) AS c FROM level0 GROUP BY block) USING (block)
UNION ALL SELECT 2, 1, n, n, c, n * c, n * c FROM (SELECT count(*) AS n FROM survivors), (SELECT count(*) AS c FROM last)"""))


def _count_ps(s: SparkSession, d: str) -> DataFrame:
    one = drawn(s, d, "orders_2d", 10, 8)
    size = one.sample.count()
    inc, full = cost.count_sampling(one.trace, 50, size, 10), cost.count_sampling(one.trace, 50, size, 10, incremental=False)
    return _values(s, [(inc["draws"], inc["pivot"], inc["prune"], full["prune"], inc["final"], cost.rounds("pivot_sampling", len(one.trace)))], "draws long, pivot long, prune long, prune_from_scratch long, final long, rounds long")


register("q_distance_count_ps", _count_ps, O.sampling("orders_2d", 10, 8, 2, """
SELECT CAST(ceil(a.m / 50.0) + ceil(b.m / 50.0) AS BIGINT) AS draws, s1 * h1 + (s1 + s2) * h2 AS pivot, CAST(ceil(a.m / 50.0) * s1 + ceil(b.m / 50.0) * s2 AS BIGINT) AS prune,
CAST(ceil(a.m / 50.0) * s1 + ceil(b.m / 50.0) * (s1 + s2) AS BIGINT) AS prune_from_scratch, 10 * (SELECT count(*) FROM sample) AS final, CAST(7 AS BIGINT) AS rounds
FROM count1 a, count2 b, (SELECT count(*) AS s1 FROM members1), (SELECT count(*) AS s2 FROM members2), (SELECT count(*) AS h1 FROM drawn1 WHERE in_h), (SELECT count(*) AS h2 FROM drawn2 WHERE in_h)"""))

# ---- generators on the tables' keys ----


def _clustered(kind: str) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        c = F.col("coords")
        return points_of(s, d, f"{kind}_on_orders").select("id", F.col("g").cast("bigint").alias("g"), *[c[i].cast("bigint").alias(f"c{i}") for i in range(3)])

    return run


for _kind in ("gauss", "skew"):
    register(f"q_{_kind}_points", _clustered(_kind), f"SELECT id, CAST(g AS BIGINT) AS g, c0, c1, c2 FROM ({O.duck_points(_kind + '_on_orders')[0]})")


def _radial(s: SparkSession, d: str) -> DataFrame:
    g, xs = clustered_sql("gauss", 25, "spark", offset="radial")
    return s.read.parquet(f"{d}/orders.parquet").selectExpr("o_orderkey AS id", f"CAST({g} AS BIGINT) AS g", *[f"{x} AS c{i}" for i, x in enumerate(xs)])


_rg, _rx = clustered_sql("gauss", 25, "duck", offset="radial")
register("q_gauss_radial_points", _radial, f"SELECT o_orderkey AS id, CAST({_rg} AS BIGINT) AS g, {', '.join(f'{x} AS c{i}' for i, x in enumerate(_rx))} FROM orders")

# ---- experiment workloads ----


def _grid_oracle(view: str, m: int = 8) -> str:
    """Radius keys of farthest-first and the two-round scheme for the whole grid of k."""
    pts, dims = O.points_cte(view)
    ctes = [pts, *O.traversal("ff", "pts", dims, max(W.KS)), f"dealt AS MATERIALIZED ({O.blocks_sql('id_mod', m)})", *O.traversal("level0", "dealt", dims, max(W.KS), "block")]
    rows = []
    for k in W.KS:
        ctes += [f"ff{k} AS MATERIALIZED (SELECT * FROM ff WHERE rank <= {k})", f"union{k} AS MATERIALIZED (SELECT DISTINCT id, {O.cs(dims)} FROM level0 WHERE rank <= {k})", *O.traversal(f"last{k}", f"union{k}", dims, k)]
        rows += [f"SELECT '{view}' AS dataset, {k} AS k, '{a}' AS alg, CAST({O.radius_key(c, dims)} AS BIGINT) AS radius_key" for a, c in (("farthest_first", f"ff{k}"), ("blocked", f"last{k}"))]
    return O.query(ctes, " UNION ALL ".join(rows))


def _grid(view: str) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        return W.radius_grid(materialised(points_of(s, d, view)), view).select("dataset", "k", "alg", F.col("radius_key").cast("bigint").alias("radius_key"))

    return run


def materialised(points: DataFrame) -> DataFrame:
    """Written in as many parts as there are cores at least: a small file of many points would leave most of them idle."""
    cores = points.sparkSession.sparkContext.defaultParallelism
    points = points.select("id", "coords")
    return materialise(points.repartition(cores) if points.rdd.getNumPartitions() < cores else points, "points")


def _with_sampling(view: str) -> Query:
    """All three methods, with iterations: which wins, and where sampling falls back to the traversal."""

    def run(s: SparkSession, d: str) -> DataFrame:
        runs = W.radius_grid(materialised(points_of(s, d, view)), view, phis=(8.0,), generator="md5")
        base = runs.where("alg = 'farthest_first'").select(F.col("k").alias("b_k"), F.col("radius").alias("base"))
        told = runs.where("alg = 'pivot_sampling'").join(base, F.col("k") == F.col("b_k"))
        return told.select("dataset", "k", F.col("radius_key").cast("bigint").alias("radius_key"), F.round(F.col("radius") / F.col("base"), 6).alias("relative"), "iterations")

    return run


def _sampling_oracle(view: str) -> str:
    pts, dims = O.points_cte(view)
    base = O.query([pts, *O.traversal("ff", "pts", dims, max(W.KS) + 1)], "SELECT rank - 1 AS k, key FROM ff WHERE rank > 1")  # the next center's key is the radius
    runs = O.all_of([O.sampled(view, k, 8, f"SELECT {k} AS k, {{radius}} AS radius_key, {{runs}} AS iterations") for k in W.KS])
    return f"SELECT '{view}' AS dataset, r.k, radius_key, round(sqrt(CAST(radius_key AS DOUBLE)) / sqrt(CAST(b.key AS DOUBLE)), 6) AS relative, iterations FROM ({runs}) r JOIN ({base}) b ON b.k = r.k"


for _w, _view in (("w1", "gauss_on_orders"), ("w2", "orders_2d"), ("w3", "skew_on_orders"), ("w4", "lineitem_grid"), ("w5", "lineitem_4d"), ("w5_events", "events_2d"), ("w22", "embeddings_64d")):
    register(f"q_workload_{_w}", _grid(_view), _grid_oracle(_view))
    register(f"q_workload_{_w}_sampling", _with_sampling(_view), _sampling_oracle(_view))


def _runtimes(view: str, ks: tuple[int, ...] | None = None, groups: int = 25, sizes: tuple[int, ...] = ()) -> Query:
    """Evaluations and times of the three methods for each k (all by default), on the view and on generated sets of the given sizes."""

    def run(s: SparkSession, d: str) -> DataFrame:
        sets = [(view, materialised(points_of(s, d, view, groups)))] + [(f"clustered_{n}", materialised(generators.gaussian_clusters(s, n, 25, scale=10_000))) for n in sizes]
        out = None
        for name, points in sets:
            t = W.runtimes(points, name, ks or W.KS).select("dataset", "alg", "n", "k", "evaluations", "sampled", "seconds", "simulated_seconds")
            out = t if out is None else out.unionByName(t)
        return out

    return run


for _w, _view, _groups in (("w6", "gauss_on_orders", 25), ("w7", "orders_2d", 25), ("w8", "gauss_on_orders", 50)):
    register(f"q_workload_{_w}_runtime", _runtimes(_view, None, _groups))
register("q_workload_w9_runtime", _runtimes("gauss_on_orders", (2, 5, 10, 12, 14, 15, 25, 50, 100), 50))  # at 15,000 points up to 14 centers are sampled
for _w, _k in (("w10", 10), ("w11", 100)):
    register(f"q_workload_{_w}_runtime", _runtimes("lineitem_4d", (_k,), sizes=(10_000, 50_000, 100_000)))


def _phi(s: SparkSession, d: str) -> DataFrame:
    sweep = W.phi_sweep(materialised(points_of(s, d, "gauss_on_orders")), generator="md5")
    return measures.best_in_row(sweep, "k", "phi", "radius_key").select("k", "phi", F.col("radius_key").cast("bigint").alias("radius_key"), "iterations", "sample_size", "is_best")


def _phi_sql() -> str:
    runs = O.all_of([O.sampled("gauss_on_orders", k, phi, f"SELECT {k} AS k, CAST({phi} AS DOUBLE) AS phi, {{radius}} AS radius_key, {{runs}} AS iterations, (SELECT count(*) FROM sample) AS sample_size") for k in W.KS for phi in W.PHIS])
    return f"SELECT *, row_number() OVER (PARTITION BY k ORDER BY radius_key, phi) = 1 AS is_best FROM ({runs})"


register("q_workload_w12_phi", _phi, _phi_sql())


def _phi_seconds(s: SparkSession, d: str) -> DataFrame:
    """Evaluations, and the time on the slowest of 50 machines, by k and phi."""
    points = materialised(points_of(s, d, "gauss_on_orders"))
    n = points.count()

    def drawn(k: int, phi: float) -> tuple:
        one = sampling.pivot_sample(points, k, phi=float(phi), n=n, generator="md5", machines=50)
        counted, took = cost.count_sampling(one.trace, 50, one.sample.count(), k), W.sampling_ns(one, k)
        return k, float(phi), len(one.trace), counted["draws"], counted["pivot"], counted["prune"], counted["final"], one.sampled, took / 1e9

    rows = W.each(drawn, [(k, phi) for k in W.KS for phi in W.PHIS])
    return _values(s, rows, "k int, phi double, iterations int, draws long, pivot long, prune long, final long, sampled boolean, simulated_seconds double")


register("q_workload_w13_phi_cost", _phi_seconds)
register("q_workload_w14_eps", lambda s, d: W.eps_sweep(materialised(points_of(s, d, "orders_2d")), 5, generator="md5").withColumn("radius_key", F.col("radius_key").cast("bigint")),
    O.all_of([O.sampled("orders_2d", 5, 8, f"SELECT CAST({e} AS DOUBLE) AS eps, {{runs}} AS iterations, (SELECT count(*) FROM sample) AS sample_size, {{radius}} AS radius_key", iterations=16, eps=e) for e in W.EPSILONS]))
SPREAD_SEEDS = (1, 2, 3)


def _spread(s: SparkSession, d: str) -> DataFrame:
    """Mean and spread of the radius over seeds, by phi."""
    points, rows = materialised(points_of(s, d, "orders_2d")), None
    for seed in SPREAD_SEEDS:
        run = W.phi_sweep(points, ks=(5,), generator="md5", seed=seed).select("phi", F.sqrt("radius_key").alias("radius"), "sample_size")
        rows = run if rows is None else rows.unionByName(run)
    told = measures.average_runs(rows, "phi")
    return told.select("phi", "repeats", *[F.round(c, 3).alias(c) for c in ("mean", "spread", "least", "most")])


register("q_workload_phi_spread", _spread, "SELECT phi, count(*) AS repeats, round(avg(r), 3) AS mean, round(stddev_samp(r), 3) AS spread, round(min(r), 3) AS least, round(max(r), 3) AS most FROM (" + O.all_of(
    [O.sampled("orders_2d", 5, p, f"SELECT CAST({p} AS DOUBLE) AS phi, sqrt(CAST({{radius}} AS DOUBLE)) AS r", seed=seed) for p in W.PHIS for seed in SPREAD_SEEDS]) + ") GROUP BY phi")


def _inherent(s: SparkSession, d: str) -> DataFrame:
    out = None
    for groups in (10, 25, 50):
        grid = W.radius_grid(materialised(points_of(s, d, "gauss_on_orders", groups)), f"gauss_{groups}", ks=(10, 25, 50))
        out = grid if out is None else out.unionByName(grid)
    return out.select("dataset", "k", "alg", F.col("radius_key").cast("bigint").alias("radius_key"))


def _inherent_sql() -> str:
    rows, ctes = [], []
    for groups in (10, 25, 50):
        sql, dims = O.duck_points("gauss_on_orders", groups)
        p = f"pts{groups}"
        ctes += [f"{p} AS MATERIALIZED ({sql})", *O.traversal(f"ff{groups}", p, dims, 50), f"dealt{groups} AS MATERIALIZED (SELECT *, id % 8 AS block FROM {p})", *O.traversal(f"level{groups}", f"dealt{groups}", dims, 50, "block")]
        for k in (10, 25, 50):
            n = f"{groups}_{k}"
            ctes += [f"ff_{n} AS MATERIALIZED (SELECT * FROM ff{groups} WHERE rank <= {k})", f"union_{n} AS MATERIALIZED (SELECT DISTINCT id, {O.cs(dims)} FROM level{groups} WHERE rank <= {k})", *O.traversal(f"last_{n}", f"union_{n}", dims, k)]
            rows += [f"SELECT 'gauss_{groups}' AS dataset, {k} AS k, '{a}' AS alg, CAST({O.radius_key(c, dims, p)} AS BIGINT) AS radius_key" for a, c in (("farthest_first", f"ff_{n}"), ("blocked", f"last_{n}"))]
    return O.query(ctes, " UNION ALL ".join(rows))


register("q_workload_w15_inherent", _inherent, _inherent_sql())
register("q_workload_w16_ties", lambda s, d: W.tie_rule_sweep(materialised(points_of(s, d, "lineitem_grid")), 5, phi=4.0, generator="md5"), O.all_of([
    O.sampled("lineitem_grid", 5, 4, f"SELECT '{rule}' AS tie_rule, {{runs}} AS iterations, (SELECT count(*) FROM live6) <= (SELECT 40 * 5 * g * l FROM size) AS terminated, (SELECT count(*) FROM live6) AS live_after", iterations=6, keep_equal=rule == "keep_equal", traverse=False)
    for rule in ("drop_equal", "keep_equal")]))
_rounds_pts, _rounds_dims = O.points_cte("lineitem_4d")
register("q_workload_w17_rounds", lambda s, d: W.rounds_sweep(materialised(points_of(s, d, "lineitem_4d")), 10, 50).withColumn("radius_key", F.col("radius_key").cast("bigint")), O.all_of([
    O.query([_rounds_pts, *O.blocked_ctes(_rounds_dims, 10, 50, more=more)], f"SELECT {len(more) + 2} AS rounds, {2 * len(more) + 4} AS guarantee, CAST({O.radius_key('last', _rounds_dims)} AS BIGINT) AS radius_key") for more in ((), (25,), (25, 12))]))
_TOLD = ("id_mod", "hash", "range", "ntile")


def _partitioners(view: str, k: int, m: int, strategies: tuple[str, ...]) -> Query:
    return lambda s, d: W.partitioner_sweep(materialised(points_of(s, d, view)), k, m, strategies).withColumn("radius_key", F.col("radius_key").cast("bigint"))


def _partitioners_sql(view: str, k: int, m: int) -> str:
    pts, dims = O.points_cte(view)
    return O.all_of([O.query([pts, *O.blocked_ctes(dims, k, m, p)], f"SELECT '{p}' AS strategy, CAST({O.radius_key('last', dims)} AS BIGINT) AS radius_key") for p in _TOLD])


for _view, _m in (("orders_2d", 8), ("embeddings_64d", 4)):
    register(f"q_workload_w18_{_view}", _partitioners(_view, 10, _m, _TOLD), _partitioners_sql(_view, 10, _m))
    register(f"q_workload_w18_{_view}_others", _partitioners(_view, 10, _m, ("random", "spatial_grid", "adversarial")))
_STARTS = (0, 100, 777, 5000)
register("q_workload_w18_seeds", lambda s, d: baselines.worst_seed(materialised(points_of(s, d, "orders_2d")), 5, list(_STARTS)).withColumn("radius_key", F.col("radius_key").cast("bigint")), O.all_of([
    O.query([_pts_orders, *O.traversal("ff", "pts", 2, 5, seed=f"CAST(id <> {start} AS INT), id")], f"SELECT CAST({start} AS BIGINT) AS seed, CAST({O.radius_key('ff', 2)} AS BIGINT) AS radius_key") for start in _STARTS]))


def _iterations_seen(s: SparkSession, d: str) -> DataFrame:
    sets = {view: materialised(points_of(s, d, view)) for view in SEEN_VIEWS}
    sizes = {view: points.count() for view, points in sets.items()}

    def seen(view: str, k: int, phi: int) -> tuple:
        one = sampling.pivot_sample(sets[view], k, phi=float(phi), n=sizes[view], generator="md5")
        return view, k, phi, len(one.trace), cost.rounds("pivot_sampling", len(one.trace))

    rows = W.each(seen, [(view, k, phi) for view in SEEN_VIEWS for k in W.KS for phi in (1, 8)])
    return _values(s, rows, "dataset string, k int, phi int, iterations int, rounds int")


SEEN_VIEWS = ("orders_2d", "gauss_on_orders", "events_2d")
register("q_workload_w19_iterations", _iterations_seen, "SELECT *, 3 * iterations + 1 AS rounds FROM (" + O.all_of(
    [O.sampled(_v, _k, _p, f"SELECT '{_v}' AS dataset, {_k} AS k, {_p} AS phi, {{runs}} AS iterations", traverse=False) for _v in SEEN_VIEWS for _k in W.KS for _p in (1, 8)]) + ")")
register("q_workload_w21_documents", lambda s, d: W.document_clusters(s, d), _with_centers(
    "SELECT n.center_id AS center_id, count(*) AS size, CAST(max(n.key) AS BIGINT) AS radius_key, count(DISTINCT lang) AS languages, CAST(sum(quality) AS BIGINT) AS n_quality, count(quality) AS n_labelled "
    "FROM assigned a JOIN documents d ON d.doc_id = a.id LEFT JOIN labels l ON l.doc_id = a.id GROUP BY 1", "documents_tf", 10))  # fmt: skip


def _runs(s: SparkSession, d: str) -> DataFrame:
    grid = W.radius_grid(materialised(points_of(s, d, "customer_2d")), "customer_2d", ks=(2, 10, 25))
    return grid.select("dataset", "k", "alg", F.col("radius_key").alias("radius"))


def _runs_sql(final: str) -> str:
    pts, dims = O.points_cte("customer_2d")
    ctes = [pts, *O.traversal("ff", "pts", dims, 25), f"dealt AS MATERIALIZED ({O.blocks_sql('id_mod', 8)})", *O.traversal("level0", "dealt", dims, 25, "block")]
    rows = []
    for k in (2, 10, 25):
        ctes += [f"ff{k} AS MATERIALIZED (SELECT * FROM ff WHERE rank <= {k})", f"union{k} AS MATERIALIZED (SELECT DISTINCT id, {O.cs(dims)} FROM level0 WHERE rank <= {k})", *O.traversal(f"last{k}", f"union{k}", dims, k)]
        rows += [f"SELECT 'customer_2d' AS dataset, {k} AS k, '{a}' AS alg, CAST({O.radius_key(c, dims)} AS DOUBLE) AS radius" for a, c in (("farthest_first", f"ff{k}"), ("blocked", f"last{k}"))]
    return O.query([*ctes, f"runs AS ({' UNION ALL '.join(rows)})"], final)


register("q_relative_value", lambda s, d: measures.relative_value(_runs(s, d)).select("dataset", "k", "alg", F.round("relative", 9).alias("relative")), _runs_sql("SELECT r.dataset, r.k, r.alg, round(r.radius / b.radius, 9) AS relative FROM runs r JOIN runs b ON b.k = r.k AND b.alg = 'farthest_first'"))
register("q_best_in_row", lambda s, d: measures.best_in_row(_runs(s, d), "k", "alg").select("k", "alg", "is_best"), _runs_sql("SELECT k, alg, row_number() OVER (PARTITION BY k ORDER BY radius, alg) = 1 AS is_best FROM runs"))
register("q_average_runs", lambda s, d: measures.average_runs(_runs(s, d), "alg").select("alg", "repeats", F.round("mean", 3).alias("mean"), "least", "most"), _runs_sql("SELECT alg, count(*) AS repeats, round(avg(radius), 3) AS mean, min(radius) AS least, max(radius) AS most FROM runs GROUP BY alg"))
register(
    "q_rollup_runs", lambda s, d: measures.rollup_runs(_runs(s, d)).select(F.coalesce("dataset", F.lit("all")).alias("dataset"), F.coalesce("alg", F.lit("all")).alias("alg"), "n_runs", F.round("mean_radius", 3).alias("mean_radius")),
    _runs_sql("SELECT coalesce(dataset, 'all') AS dataset, coalesce(alg, 'all') AS alg, count(*) AS n_runs, round(avg(radius), 3) AS mean_radius FROM runs GROUP BY ROLLUP (dataset, alg)"),
)

# ---- SQL, ML and streaming surfaces ----


def _udtf(s: SparkSession, d: str) -> DataFrame:
    from farpoint.functions.sql import register_sql

    register_sql(s)
    points_of(s, d, "orders_2d").select("id", "coords").createOrReplaceTempView("farpoint_orders_2d")
    return picked(s.sql("SELECT * FROM k_center(TABLE(farpoint_orders_2d) WITH SINGLE PARTITION, 10)"))


register("q_sql_udtf_orders", _udtf, O.farthest_first("orders_2d", 10))


def _euclid(s: SparkSession, d: str) -> DataFrame:
    from farpoint.functions.sql import register_sql

    register_sql(s)
    points_of(s, d, "nation_tiny").createOrReplaceTempView("farpoint_nation")
    return s.sql("SELECT a.id AS a, b.id AS b, round(euclid(a.coords, b.coords), 9) AS distance, CAST(manhattan(a.coords, b.coords) AS BIGINT) AS blocks FROM farpoint_nation a JOIN farpoint_nation b ON a.id < b.id")


register("q_sql_euclid_nation", _euclid, O.query([O.points_cte("nation_tiny")[0]], f"SELECT a.id AS a, b.id AS b, round(sqrt({O.squared('a', 'b', 2)}), 9) AS distance, CAST({O.manhattan('a', 'b', 2)} AS BIGINT) AS blocks FROM pts a JOIN pts b ON a.id < b.id"))


def _ml(s: SparkSession, d: str) -> DataFrame:
    from farpoint.operators.mlapi import KCenter

    p = points_of(s, d, "customer_2d").select("id", "coords")
    return KCenter(k=25, algorithm="farthest_first").fit(p).transform(p).groupBy("center_id").agg(F.count("*").alias("size"))


register("q_ml_kcenter_customer", _ml, _with_centers("SELECT n.center_id AS center_id, count(*) AS size FROM assigned GROUP BY 1", "customer_2d", 25))
register("q_cube_runs", lambda s, d: measures.cube_runs(_runs(s, d)).select(F.coalesce("alg", F.lit("all")).alias("alg"), F.coalesce("k", F.lit(0)).alias("k"), "n_runs", F.round("mean_radius", 3).alias("mean_radius")), _runs_sql("SELECT coalesce(alg, 'all') AS alg, coalesce(k, 0) AS k, count(*) AS n_runs, round(avg(radius), 3) AS mean_radius FROM runs GROUP BY CUBE (alg, k)"))
register("q_grouping_sets_runs", lambda s, d: measures.grouping_sets_runs(_runs(s, d)).select(F.coalesce("alg", F.lit("all")).alias("alg"), F.coalesce("k", F.lit(0)).alias("k"), F.round("mean_radius", 3).alias("mean_radius")), _runs_sql("SELECT coalesce(alg, 'all') AS alg, coalesce(k, 0) AS k, round(avg(radius), 3) AS mean_radius FROM runs GROUP BY GROUPING SETS ((alg), (k))"))


def _overlap(s: SparkSession, d: str) -> DataFrame:
    p = points_of(s, d, "orders_2d")
    return measures.center_overlap(farthest_first(p, 25), blocked_farthest_first(p, 25, 8).centers)


def _overlap_sql() -> str:
    pts, dims = O.points_cte("orders_2d")
    return O.query([pts, *O.traversal("ff", "pts", dims, 25), *O.blocked_ctes(dims, 25, 8)], "SELECT count(*) FILTER (WHERE a.id IS NOT NULL AND b.id IS NOT NULL) AS both, count(*) FILTER (WHERE b.id IS NULL) AS only_a, count(*) FILTER (WHERE a.id IS NULL) AS only_b FROM ff a FULL JOIN last b ON a.id = b.id")


register("q_center_overlap_orders", _overlap, _overlap_sql())
register(
    "q_farthest_per_cluster_customer", lambda s, d: A.farthest_per_cluster(_served(s, d, "customer_2d", 25), 3),
    _with_centers("SELECT center_id, place, id, key FROM (SELECT n.center_id AS center_id, id, CAST(n.key AS BIGINT) AS key, row_number() OVER (PARTITION BY n.center_id ORDER BY n.key DESC, id) AS place FROM assigned) WHERE place <= 3", "customer_2d", 25),
)
register("q_distance_profile_orders", lambda s, d: A.distance_profile(_served(s, d)))


def _streamed(s: SparkSession, d: str) -> DataFrame:
    """Centers of the events read as a stream; its batches are the levels' sets."""
    from farpoint.streaming.kcenter_stream import stream_kcenter

    sink, query = stream_kcenter(stream_of(s, d, "events_2d"), 10, f"{shared_dir(s)}/stream-{uuid.uuid4().hex}")
    try:
        query.processAllAvailable()
    finally:
        query.stop()
    ids, _ = sink.levels.centers()
    return _values(s, [(i, int(x)) for i, x in enumerate(ids, 1)], "rank long, id long")


register("q_stream_events", _streamed, O.blocked("events_2d", 10, 8, final="SELECT CAST(rank AS BIGINT) AS rank, id FROM last"))  # one file is one batch


def _udf_assign(s: SparkSession, d: str) -> DataFrame:
    p = points_of(s, d, "customer_2d")
    near = A.nearest_center_udf(farthest_first(p, 25))
    return p.select("id", near("coords").alias("center_id"))


register("q_udf_nearest_customer", _udf_assign, _with_centers("SELECT id, n.center_id AS center_id FROM assigned", "customer_2d", 25))


def _planned(s: SparkSession, d: str) -> DataFrame:
    """An instance through its plan: the blocked scheme with levels for a small capacity."""
    from farpoint.plans.plan import make_plan, solve
    from farpoint.plans.problem import KCenterProblem

    problem = KCenterProblem(points_of(s, d, "orders_2d"), 10)
    plan = make_plan(problem.points.count(), 10, 8, algorithm="blocked")
    return picked(solve(problem, plan, strategy="id_mod").centers)


register("q_planned_orders", _planned, O.blocked("orders_2d", 10, 8))
