"""SQL surface: a table function for centers, a distance function, a scalar nearest-center function."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

POINT = "ARRAY<DOUBLE>"


@udtf(returnType="rank int, id bigint, coords array<double>, key double")
class KCenterTable:
    """k_center(TABLE(points) WITH SINGLE PARTITION | PARTITION BY ..., k => 10 [, measure => 'euclidean'])

    The table's first columns are id and coords. A partition is one problem and fits into a task.
    """

    def __init__(self):
        self.ids, self.rows, self.k, self.measure = [], [], 1, "euclidean"

    def eval(self, row, k, measure="euclidean"):
        self.k, self.measure = k, measure
        self.ids.append(row[0])
        self.rows.append(row[1])

    def terminate(self):
        import numpy as np

        from farpoint.operators import kernels

        if not self.ids:
            return
        ids, x = kernels.by_id(np.array(self.ids, np.int64), np.array(self.rows, float))
        picks, keys, _ = kernels.farthest_first(x, self.k, 0, 0.0, self.measure)
        for rank, (at, key) in enumerate(zip(picks.tolist(), keys.tolist(), strict=True), 1):
            yield rank, int(ids[at]), x[at].tolist(), None if key == float("inf") else key


def register_sql(spark: SparkSession) -> None:
    """k_center, euclid, sq_euclid and manhattan for SQL; the scalar ones are inlined by the optimizer."""
    spark.udtf.register("k_center", KCenterTable)
    for name, body in (
        ("sq_euclid", "aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, v) -> s + v)"),
        ("euclid", "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, v) -> s + v))"),
        ("manhattan", "aggregate(zip_with(a, b, (x, y) -> abs(x - y)), 0D, (s, v) -> s + v)"),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(a {POINT}, b {POINT}) RETURNS DOUBLE RETURN {body}")
