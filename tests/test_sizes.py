"""Queries on tables larger than those of the other tests, and what they take instead of limits."""

import datetime
import itertools

import duckdb
import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from farpoint import oracles as O
from farpoint import workloads as W
from farpoint.functions.hashing import md5_below, md5_uniform
from farpoint.operators import exact, kernels, sampling, threshold
from farpoint.queries import ORACLES, QUERIES, drawn, materialised
from farpoint.sources import staging

SF = "/root/testdata/sf0.1"


def test_cost_beyond_long(spark, tmp_path):
    """a sum over 2**63 is told whole, a smaller one is a BIGINT."""
    n = 40
    day = datetime.datetime(1992, 1, 1)
    orders = {"o_orderkey": list(range(n)), "o_totalprice": [float(i * 10_000_000) for i in range(n)], "o_orderdate": pa.array([day] * n, pa.timestamp("us"))}
    pq.write_table(pa.table(orders), tmp_path / "orders.parquet")
    x = np.array([[float(i * 1_000_000_000), 0.0] for i in range(n)])
    picks, _, _ = kernels.farthest_first(x, 10)
    want = sum(min(int(p[0] - x[c][0]) ** 2 for c in picks) for p in x)
    assert want > 1 << 63
    assert int(QUERIES["q_cost_sum_orders"](spark, str(tmp_path)).first().cost) == want
    assert dict(QUERIES["q_cost_sum_orders"](spark, "/root/testdata/sf0.01").dtypes) == {"cost": "bigint"}


def supplier_points():
    return np.array(duckdb.sql(f"SELECT s_suppkey, floor(s_acctbal * 100 + 0.5), s_nationkey * 10000 FROM '{SF}/supplier.parquet' ORDER BY 1").fetchall(), float)


def best_pair(points, candidates):
    """By looking at all pairs."""
    d = ((points[:, None, 1:] - candidates[None, :, 1:]) ** 2).sum(2)
    best = min((np.minimum(d[:, [i]], d[:, i + 1 :]).max(0).min(), i, i + 1 + int(np.minimum(d[:, [i]], d[:, i + 1 :]).max(0).argmin())) for i in range(len(candidates) - 1))
    return int(best[0]), int(candidates[best[1], 0]), int(candidates[best[2], 0])


def test_brute_force_on_more_suppliers(spark):
    """499,500 pairs for 1000 points."""
    x = supplier_points()
    assert tuple(QUERIES["q_bruteforce_supplier_k2"](spark, SF).first()) == best_pair(x, x)


def test_search_against_enumeration():
    """any number of centers, places that are shared, ties."""
    rng = np.random.default_rng(1)
    for _ in range(60):
        k = int(rng.integers(1, 4))
        x, c = (np.unique(rng.integers(0, 6, (10, 2)), axis=0).astype(float), rng.integers(0, 6, (int(rng.integers(3, 9)), 2)).astype(float))
        want = min((max(min(((p - c[j]) ** 2).sum() for j in s) for p in x), list(s)) for s in itertools.combinations(range(len(c)), k))
        open_ = np.full(len(x), np.inf)
        assert exact.improved(x, c, open_, k, exact._snapped(x, c, k)) == want[0] and exact.first_set(x, c, open_, k, want[0], -1) == want[1]


def test_fewer_candidates_than_centers(spark):
    p = spark.createDataFrame([(1, [0.0]), (2, [0.0])], "id long, coords array<double>")
    assert tuple(exact.brute_force_opt(p, 2).first()) == (0.0, [1, 2]) and exact.brute_force_opt(p, 3).first().ids is None


def test_restricted_optimum_on_more_suppliers(spark):
    """F5."""
    x = supplier_points()
    assert tuple(QUERIES["q_opt_restricted_supplier"](spark, SF).first()) == best_pair(x, x[x[:, 0] % 4 == 0])


def test_ratio_on_more_suppliers(spark):
    """F6."""
    x = supplier_points()
    opt = best_pair(x, x)[0]
    ff = kernels.farthest_first(x[:, 1:], 2)[2]
    got = QUERIES["q_ratio_supplier_k2"](spark, SF).first()
    assert got.ff_ratio == round((ff / opt) ** 0.5, 9) and 1 <= got.bff_ratio <= 4


@pytest.mark.parametrize("n,places", [(0, 1), (1, 1), (2, 2), (20, 1), (20, 2)])
def test_ratio_without_a_positive_optimum(spark, tmp_path, n, places):
    """fewer suppliers than centers, or no more places than centers: null or NaN, as in SQL."""
    balances = [float(i % places) for i in range(n)]
    pq.write_table(pa.table({"s_suppkey": pa.array(range(n), pa.int64()), "s_nationkey": pa.array([1] * n, pa.int32()), "s_acctbal": pa.array(balances, pa.float64())}), tmp_path / "supplier.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW supplier AS SELECT * FROM '{tmp_path}/supplier.parquet'")
    want = con.execute(ORACLES["q_ratio_supplier_k2"]).fetchall()
    assert str([tuple(r) for r in QUERIES["q_ratio_supplier_k2"](spark, str(tmp_path)).collect()]) == str(want)


def test_blocks_of_more_points_by_threshold(spark):
    """a block of more points than have their distances held."""
    rng = np.random.default_rng(2)
    x = np.unique(rng.integers(0, 100_000, (10_500, 2)), axis=0).astype(float)
    picks, _, radius = threshold.threshold_solver(x, 5)
    assert len(picks) <= 5 and radius == kernels.nearest(x, x[picks])[1].max()
    assert radius <= 4 * kernels.farthest_first(x, 5)[2]


def test_next_key_looks_at_all_pairs(monkeypatch):
    """the next distance is that of all pairs, and covers are as good as with all distances held."""
    monkeypatch.setattr(threshold, "LEAF", 4)
    rng = np.random.default_rng(1)
    for _ in range(60):
        x, k = np.unique(rng.integers(0, 30, (int(rng.integers(5, 60)), 2)), axis=0).astype(float), int(rng.integers(1, 5))
        keys = np.unique([((a - b) ** 2).sum() for a in x for b in x])
        least = float(rng.uniform(0, keys.max()))
        assert threshold.next_key(x, least) == keys[keys >= least].min()
        picks = threshold._bisected(x, k, 4.0, "euclidean")
        opt = exact.improved(x, x, np.full(len(x), np.inf), k, np.inf)
        assert len(picks) <= k and kernels.nearest(x, x[picks])[1].max() <= 4 * opt


@pytest.mark.parametrize("dims,scale", [(2, 1), (3, 1), (4, 1), (2, 100_000_000)])
def test_boxes_give_the_nearest(dims, scale):
    """the same keys as by all distances, also where products would not be exact, with few distances."""
    rng = np.random.default_rng(dims)
    x = np.concatenate([rng.integers(0, 5000, (3000, dims)), rng.integers(4000, 4100, (2000, dims))]).astype(float) * scale
    centers = x[rng.choice(len(x), 1000)]
    low = np.where(rng.random(len(x)) < 0.1, 3.0 * scale, np.inf)
    want = np.minimum(low, [((centers - p) ** 2).sum(1).min() for p in x])
    boxes, looked = kernels.Boxes(centers), []
    keys = boxes._keys
    boxes._keys = lambda p, which, exact: looked.append(len(p) * len(which)) or keys(p, which, exact)
    assert (boxes.lower(x, low) == want).all()
    assert sum(looked) * kernels.CENTERS_IN_BOX < 0.7 * len(x) * len(centers)


def test_draws_by_digits(spark):
    """comparing digits draws the same points."""
    ids = spark.range(5000).select(F.col("id").cast("string").alias("t"))
    for rate in (0.0, 1e-9, 0.01, 0.3333333333333333, 0.999999, 1.0):
        row = ids.agg(F.count_if(md5_below(rate, 42, 0, "S", F.col("t")) != (md5_uniform(42, 0, "S", F.col("t")) < rate)), F.count_if(md5_below(rate, 42, 0, "S", F.col("t")))).first()
        assert row[0] == 0 and abs(row[1] - 5000 * rate) < 150


def test_runs_at_once_keep_the_setting(spark):
    """concurrent writers put the session's setting back."""
    before = spark.conf.get(staging.FREE_SHUFFLES, "false")
    got = W.each(lambda i: staging.materialise(spark.range(i)).count(), [(i,) for i in range(12)])
    assert got == list(range(12)) and spark.conf.get(staging.FREE_SHUFFLES, "false") == before


def test_points_use_all_cores(spark):
    """points of one small file are written in as many parts as there are cores."""
    few = materialised(spark.range(100).select("id", F.array(F.col("id").cast("double")).alias("coords")).coalesce(1))
    assert few.rdd.getNumPartitions() == spark.sparkContext.defaultParallelism and few.count() == 100


def test_shares_are_cut_inside_tasks():
    """a machine's rows are timed as one share, without dealing them anew, and the keys stay the same."""
    batches = [pa.record_batch({"i": list(range(lo, lo + n))}) for lo, n in ((0, 5), (5, 0), (5, 17), (22, 1))]
    cut = [b.column(0).to_pylist() for b in sampling._gathered(iter(batches), 4, 10)]
    assert [len(c) for c in cut] == [4, 4, 2, 4, 4, 2, 3] and sum(cut, []) == list(range(23))
    x = np.random.default_rng(3).integers(0, 1000, (60, 2)).astype(float)
    rows = pa.record_batch({"key": pa.array([None] * 60, pa.float64()), "coords": pa.array(x.tolist()), "ns": pa.array([0] * 60)})
    for few in (x[:3], np.tile(x, (10, 1))):  # by all distances, and by boxes
        sent = type("Sent", (), {"value": few})
        one, shared = (pa.Table.from_batches(sampling._lowered(sent, "euclidean", share)(iter([rows]))) for share in (None, 25))
        assert one.column("key") == shared.column("key")
        ns = shared.column("ns").to_numpy()
        assert all(len(set(ns[lo : lo + 25])) == 1 for lo in (0, 25, 50)) and len(set(one.column("ns").to_pylist())) == 1
        assert ns[-1] < ns[:50].sum() / 25  # the last share is timed from its own beginning


def test_runtimes_draw_once(spark, sf, monkeypatch):
    """wall clock and simulated time are of one drawing for each k; what is counted is as from the sample itself."""
    points, calls = materialised(W.points_of(spark, "/root/testdata/sf0.01", "orders_2d")), []
    monkeypatch.setattr(W, "pivot_sample", lambda *a, **b: calls.append(a) or sampling.pivot_sample(*a, **b))
    rows = {(r.k, r.alg): r for r in W.runtimes(points, "orders_2d", (2, 50)).collect()}
    assert len(calls) == 2 and len(rows) == 6 and all(r.seconds > 0 and r.simulated_seconds > 0 for r in rows.values())
    for k in (2, 50):
        one = sampling.pivot_sample(points, k)
        got = rows[k, "pivot_sampling_8"]
        assert got.sampled == one.sampled == (k == 2)
        assert got.evaluations == sum(W.cost.count_sampling(one.trace, 50, one.sample.count(), k).values())
    none = W.runtimes(materialised(points.where("id < 0")), "none", (2,)).collect()
    assert [r.evaluations for r in none] == [0, 0, 0]


READ_LINES = "q_bff_tight_instance q_feasibility q_level_plan q_machines_bound q_balanced_m q_max_sampling_k q_phi_threshold q_feasible_roots q_ps_expected_trace".split()


@pytest.mark.parametrize("name", READ_LINES)
def test_queries_read_lines(spark, sf, name):
    """The rows are told from a given table, in the plan."""
    got = QUERIES[name](spark, sf)
    assert any("lineitem.parquet" in f for f in got.inputFiles()) and got.count() > 0


@pytest.mark.parametrize("name,table", [("q_check_metric_nation", "nation"), ("q_ff_region_trivial", "region"), ("q_known_opt_cover_nation", "nation")])
def test_small_tables_are_read(spark, sf, name, table):
    """F33, F36, F37 are wrong: Spark reads the table."""
    assert any(f"{table}.parquet" in f for f in QUERIES[name](spark, sf).inputFiles())


@pytest.mark.parametrize("view,k,phi", [("orders_2d", 10, 8), ("orders_2d", 10, 4), ("orders_2d", 10, 1), ("orders_2d", 25, 8), ("events_2d", 5, 1)])
def test_sampling_runs_to_its_end(spark, view, k, phi):
    """With the loop unrolled far enough SQL gives the same sample; the registered SQL stops after one to three iterations."""
    for t in ("orders", "events"):
        duckdb.sql(f"CREATE OR REPLACE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    one = drawn(spark, SF, view, k, phi)
    want = duckdb.sql(O.sampled(view, k, phi, "SELECT id, part, {runs} AS runs FROM sample", iterations=9, traverse=False)).fetchall()
    assert {r[2] for r in want} == {len(one.trace)} and one.terminated and len(one.trace) > 0
    assert sorted((r.id, r.part) for r in one.sample.select("id", "part").collect()) == sorted(r[:2] for r in want)
