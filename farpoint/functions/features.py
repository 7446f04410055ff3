"""Columns to coordinates: fixed-point scaling, categories, standardising, hashed term counts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def to_points(df: DataFrame, id_col: str, columns: list[str], scale: dict[str, float] | float | None = None) -> DataFrame:
    """id, coords. With a scale, a column becomes floor(v * scale + 0.5), a whole number."""
    parts = []
    for c in columns:
        s = scale.get(c) if isinstance(scale, dict) else scale
        parts.append((F.floor(F.col(c) * s + 0.5) if s else F.col(c)).cast("double"))
    return df.select(F.col(id_col).cast("long").alias("id"), F.array(*parts).alias("coords"))


def encode_ordinal(df: DataFrame, column: str, out: str, most: int = 100_000) -> DataFrame:
    """A number for each value of a category, in sorted order; the list of values is bounded by ``most``."""
    values = [r[0] for r in df.select(column).where(F.col(column).isNotNull()).distinct().orderBy(column).limit(most + 1).collect()]
    if len(values) > most:
        raise ValueError(f"{column} has over {most} values")
    return df.withColumn(out, F.array_position(F.array(*[F.lit(v) for v in values]), F.col(column)) - 1)


def encode_one_hot(df: DataFrame, column: str, values: list) -> DataFrame:
    """A 0/1 column for each of the values."""
    return df.withColumns({f"{column}_{v}": F.coalesce((F.col(column) == F.lit(v)).cast("double"), F.lit(0.0)) for v in values})


def standardize(points: DataFrame, dims: int) -> DataFrame:
    """Coordinates less their mean, over their standard deviation (constant ones become 0)."""
    c = F.col("coords")
    stats = points.agg(*[f(c[i]).alias(f"{n}{i}") for i in range(dims) for n, f in (("m", F.avg), ("s", F.stddev_pop))]).first()
    return points.withColumn("coords", F.array(*[(c[i] - stats[f"m{i}"]) / stats[f"s{i}"] if stats[f"s{i}"] else F.lit(0.0) for i in range(dims)]))


def min_max(points: DataFrame, dims: int) -> DataFrame:
    """Coordinates mapped to [0, 1]."""
    c = F.col("coords")
    stats = points.agg(*[f(c[i]).alias(f"{n}{i}") for i in range(dims) for n, f in (("lo", F.min), ("hi", F.max))]).first()
    return points.withColumn("coords", F.array(*[(c[i] - stats[f"lo{i}"]) / (stats[f"hi{i}"] - stats[f"lo{i}"]) if stats[f"hi{i}"] > stats[f"lo{i}"] else F.lit(0.0) for i in range(dims)]))


def term_counts(texts: DataFrame, buckets: int = 32) -> DataFrame:
    """id, text -> id, coords: counts of the words (split at single spaces, A-Z lower-cased) by hash bucket."""
    lower = F.translate("text", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    words = texts.select("id", F.explode(F.split(lower, " ")).alias("w"))
    b = F.pmod(F.conv(F.substring(F.md5(F.col("w").cast("binary")), 1, 4), 16, 10).cast("int"), F.lit(buckets))
    counts = words.select("id", b.alias("b")).groupBy("id").agg(*[F.count_if(F.col("b") == i).cast("double").alias(f"b{i}") for i in range(buckets)])
    return counts.select("id", F.array(*[f"b{i}" for i in range(buckets)]).alias("coords"))
