"""Shared pieces of the training-data operators: reading, staging, null-safe keys."""

from __future__ import annotations

import contextlib
import uuid
from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from farpoint.sources.staging import shared_dir

#: White space of the text contracts, as a Java regular expression.
SPACE_RUN = r"[\x20\x09-\x0D]+"

#: Runtime settings of a staged write: the table takes the place of the shuffle files, and batches of
#: whole texts stay small in the Python workers.
WHILE_WRITING = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true", "spark.sql.execution.arrow.maxRecordsPerBatch": "2000"}


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


class Staging:
    """Tables written to the shared folder: they cut lineage and outlive lost executors."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.root = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
        self._n = 0

    def path(self, table: str) -> str:
        self._n += 1
        return f"{self.root}/{table}-{self._n}"

    def keep(self, df: DataFrame, table: str, codec: str = "zstd") -> DataFrame:
        path = self.path(table)
        before = {k: self.spark.conf.get(k) for k in WHILE_WRITING}
        try:
            for k, v in WHILE_WRITING.items():
                self.spark.conf.set(k, v)
            df.write.option("compression", codec).parquet(path)
        finally:
            for k, v in before.items():
                self.spark.conf.set(k, v)
        kept = self.spark.read.schema(df.schema).parquet(path)
        kept.staged_path = path
        return kept

    def drop(self, *kept: DataFrame) -> None:
        """Deletes tables that no later plan reads."""
        for table in kept:
            self.delete(table.staged_path)

    @contextlib.contextmanager
    def scratch(self) -> Iterator[Staging]:
        """A place for tables that nothing reads after the block; what the result reads is kept outside."""
        inner = Staging(self.spark, "scratch")
        inner.root = self.path("scratch")
        try:
            yield inner
        finally:
            self.delete(inner.root)

    def delete(self, path: str) -> None:
        jvm = self.spark._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(where, True)


def text_hash(text: str = "text") -> Column:
    """With the id, what tells rows apart: rows equal in both are judged alike."""
    return F.unhex(F.md5(F.col(text).cast("string").cast("binary")))


def without_rows(stage: Staging, docs: DataFrame, gone: DataFrame, limit: int = 1_000_000) -> DataFrame:
    """``docs`` without the rows whose id and text hash are in the two columns of ``gone``; the texts are not moved while those are few."""
    gone = stage.keep(gone.toDF("__gone", "__hash").distinct(), "gone")
    side = F.broadcast(gone) if gone.count() <= limit else gone
    return docs.join(side, docs["doc_id"].eqNullSafe(side["__gone"]) & text_hash().eqNullSafe(side["__hash"]), "left_anti")


def ascii_lower(col: Column) -> Column:
    """Lower-cases A-Z and nothing else."""
    return F.translate(col, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def repeat_rows(df: DataFrame, count: str) -> DataFrame:
    """Each row ``count`` times, numbered from 1 in ``copy_no``."""
    return df.withColumn("copy_no", F.explode(F.sequence(F.lit(1).cast("long"), F.col(count)))).drop(count)
