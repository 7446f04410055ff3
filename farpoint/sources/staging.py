"""Tables in the folder that driver and executors share; they cut the lineage of driver loops."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import threading
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

FREE_SHUFFLES = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_own: dict[str, str] = {}
_lock, _writers, _before = threading.Lock(), [], []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``, or the folder of setCheckpointDir.

    Where neither is set a temporary folder is made, but only for a local master; on a cluster that would be
    a folder of one machine, so it is an error there.
    """
    configured = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if configured:
        return configured.rstrip("/")
    app = spark.sparkContext.applicationId
    with _lock:
        if app not in _own:
            if not spark.sparkContext.master.startswith("local"):
                raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
            _own[app] = tempfile.mkdtemp(prefix="farpoint-")
            atexit.register(shutil.rmtree, _own[app], True)
    return f"file://{_own[app]}"


@contextmanager
def _freeing_shuffles(spark: SparkSession) -> Iterator[None]:
    """The setting holds while anyone writes; the last writer puts back what it was before the first."""
    with _lock:
        if not _writers:
            _before[:] = [spark.conf.get(FREE_SHUFFLES, "false")]
            spark.conf.set(FREE_SHUFFLES, "true")
        _writers.append(1)
    try:
        yield
    finally:
        with _lock:
            _writers.pop()
            if not _writers:
                spark.conf.set(FREE_SHUFFLES, _before[0])


def materialise(df: DataFrame, name: str = "table") -> DataFrame:
    """Writes ``df`` and reads it back. Retries and later jobs read the files, so an executor may go."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    with _freeing_shuffles(spark):
        df.write.parquet(path)
    kept = spark.read.schema(df.schema).parquet(path)
    kept.staged_path = path
    return kept


def release(kept: DataFrame) -> None:
    """Deletes a materialised table that no later plan reads."""
    spark = kept.sparkSession
    where = spark._jvm.org.apache.hadoop.fs.Path(kept.staged_path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)
