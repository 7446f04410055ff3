"""Reading points and edges, writing results, and a Python data source of synthetic points."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from farpoint.functions.features import to_points


def read_points(spark: SparkSession, fmt: str, path: str, schema: str, id_col: str, columns: list[str], scale: dict[str, float] | float | None = None, **options) -> DataFrame:
    """id, coords from parquet, orc, csv, json or any other format of Spark, with the schema given."""
    return to_points(spark.read.format(fmt).schema(schema).options(**options).load(path), id_col, columns, scale)


def read_text_points(spark: SparkSession, path: str, dims: int, sep: str = r"\s+") -> DataFrame:
    """Lines ``id v1 v2 ...``."""
    parts = spark.read.text(path).select(F.split(F.trim("value"), sep).alias("p")).where(F.size("p") == dims + 1)
    return parts.select(F.col("p")[0].cast("long").alias("id"), F.array(*[F.col("p")[i + 1].cast("double") for i in range(dims)]).alias("coords"))


def points_from_rows(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    """[(id, [v1, v2, ...]), ...]"""
    return spark.createDataFrame([(int(i), [float(v) for v in x]) for i, x in rows], "id long, coords array<double>")


def points_from_table(spark: SparkSession, name: str, id_col: str, columns: list[str], scale: dict[str, float] | float | None = None) -> DataFrame:
    return to_points(spark.table(name), id_col, columns, scale)


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """u, v, w of a complete graph; each edge may be given once, both directions come out."""
    e = spark.read.format(fmt).load(path).select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"), F.col("w").cast("double").alias("w"))
    return e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v"), "w")).distinct()


def write_result(df: DataFrame, path: str, partition_by: str | None = None, mode: str = "overwrite", fmt: str = "parquet") -> None:
    """Centers, assignments (partitioned by center_id), traces and run logs."""
    writer = df.write.mode(mode).format(fmt)
    (writer.partitionBy(partition_by) if partition_by else writer).save(path)


def run_only(df: DataFrame) -> None:
    """Runs a plan without keeping its rows, for timing."""
    df.write.format("noop").mode("overwrite").save()


class _Range(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class SyntheticPoints(DataSource):
    """``spark.read.format("farpoint_synth")`` with options n, dims, side, seed, partitions: uniform points."""

    @classmethod
    def name(cls) -> str:
        return "farpoint_synth"

    def schema(self) -> str:
        return "id long, coords array<double>"

    def reader(self, schema) -> DataSourceReader:
        return _SyntheticReader(self.options)


class _SyntheticReader(DataSourceReader):
    def __init__(self, options):
        self.n, self.dims = int(options.get("n", 1000)), int(options.get("dims", 2))
        self.side, self.seed, self.parts = float(options.get("side", 100)), int(options.get("seed", 1)), int(options.get("partitions", 8))

    def partitions(self):
        step = -(-self.n // self.parts) or 1
        return [_Range(lo, min(lo + step, self.n)) for lo in range(0, max(self.n, 1), step)]

    def read(self, partition):
        import numpy as np
        import pyarrow as pa

        for lo in range(partition.first, partition.last, 65_536):
            ids = np.arange(lo, min(lo + 65_536, partition.last), dtype=np.uint64)
            columns = []
            for d in range(self.dims):
                with np.errstate(over="ignore"):
                    x = ids * np.uint64(0x9E3779B97F4A7C15) + np.uint64(self.seed * 1_000_003 + d + 1)
                    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
                    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
                columns.append((x >> np.uint64(11)) * 2.0**-53 * self.side)
            flat = pa.array(np.stack(columns, 1).reshape(-1))
            coords = pa.ListArray.from_arrays(pa.array(np.arange(0, len(flat) + 1, self.dims), pa.int32()), flat)
            yield pa.RecordBatch.from_arrays([pa.array(ids.astype(np.int64)), coords], names=["id", "coords"])
