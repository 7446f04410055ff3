"""Every query of the k-center methods that has a DuckDB form, row for row, and a run of the others."""

import math

import duckdb
import pytest

from farpoint import workloads as W
from farpoint.queries import ORACLES, QUERIES

SF = "/root/testdata/sf0.01"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
TIMED = [n for n in QUERIES if n.endswith("_runtime") or n == "q_workload_w13_phi_cost"]  # times have no SQL; run on the smallest tables


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


def rows(columns, values):
    def cell(v):
        if v is None or (isinstance(v, float) and math.isnan(v)):
            return None
        return float(v) if isinstance(v, (int, float)) and not isinstance(v, bool) else v

    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(str([cell(r[i]) for i in order]) for r in values)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracle(spark, duck, name):
    got = QUERIES[name](spark, SF)
    want = duck.sql(ORACLES[name])
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got.columns, got.collect()) == rows(want.columns, want.fetchall())


@pytest.mark.parametrize("name", sorted(n for n in QUERIES if n not in ORACLES and n not in TIMED))
def test_others_run(spark, name):
    assert QUERIES[name](spark, SF).count() > 0


@pytest.mark.parametrize("name", [n for n in TIMED if not n.startswith(("q_workload_w9", "q_workload_w10", "q_workload_w11"))])
def test_timed_run(spark, sf, name, monkeypatch):
    monkeypatch.setattr(W, "KS", (2, 5))
    rows = QUERIES[name](spark, sf).collect()
    assert rows and all(r.simulated_seconds > 0 for r in rows)


def test_which_method_wins(spark):
    """Sampling is nearly as good or better, and falls back to the traversal where k is large for n."""
    blocked = {(r.k, r.alg): r.radius_key for r in QUERIES["q_workload_w1"](spark, SF).collect()}
    got = {r.k: r for r in QUERIES["q_workload_w1_sampling"](spark, SF).collect()}
    for k in (2, 5, 10, 25):
        assert 0.5 <= math.sqrt(blocked[k, "blocked"] / blocked[k, "farthest_first"]) <= 1.5 and 0.5 <= got[k].relative <= 1.5
    assert got[25].iterations == got[50].iterations == got[100].iterations == 0 and got[25].relative == got[100].relative == 1
    assert got[2].iterations > got[10].iterations > 0
    assert blocked[10, "farthest_first"] > 400 * blocked[25, "farthest_first"]  # the inherent number of clusters


def test_smaller_phi_samples_less(spark):
    rows = QUERIES["q_workload_w12_phi"](spark, SF).collect()
    for k in (2, 10):
        of = sorted((r.phi, r.iterations, r.sample_size) for r in rows if r.k == k)
        assert [i for _, i, _ in of] == sorted(i for _, i, _ in of) and of[0][2] < of[-1][2]


def test_dominant_rounds_grow_with_k(spark):
    """The pruning round does most of the work, and more centers mean more of it."""
    rows = {r["name"]: r for r in QUERIES["q_ps_round_slopes"](spark, SF).collect()}
    assert rows["prune"].slope > rows["draw"].slope
