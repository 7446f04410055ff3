import duckdb
import pytest

from farpoint.llm.queries import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"


def test_all_ten_are_registered():
    assert sorted(int(n[2:].split("_")[0]) for n in QUERIES) == list(range(1, 11))


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracle(spark, name):
    c = duckdb.connect()
    for t in ("documents", "pages", "benchmark", "conversations"):
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    got, want = QUERIES[name](spark, SF), c.sql(ORACLES[name])
    order = sorted(got.columns)
    assert order == sorted(want.columns)
    pick = lambda columns, rows: sorted(str([r[list(columns).index(k)] for k in order]) for r in rows)
    assert pick(got.columns, got.collect()) == pick(want.columns, want.fetchall())
