"""Cutting lineage: tables written to the shared folder that the cluster names, read back as files."""

from __future__ import annotations

import atexit
import re
import threading
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

#: Has Spark delete an execution's shuffle files when it ends, not when the driver happens to collect its garbage.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_lock, _writers = threading.Lock(), {}


@contextmanager
def tidy(spark: SparkSession):
    """What is written inside leaves no shuffle files behind; the session's own setting comes back with the last writer."""
    at = spark.sparkContext.applicationId
    with _lock:
        n, before = _writers.get(at, (0, None))
        if not n:
            before = spark.conf.get(CLEANUP, "false")
            spark.conf.set(CLEANUP, "true")
        _writers[at] = n + 1, before
    try:
        yield
    finally:
        with _lock:
            n, before = _writers[at]
            _writers[at] = n - 1, before
            if n == 1:
                spark.conf.set(CLEANUP, before)


_written: list[tuple[SparkSession, str]] = []


def root(spark: SparkSession) -> str:
    """spark.checkpoint.dir; a folder of our own only on a local master that names none (tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    return named or "file:///tmp/checkpoints/attrition-core"


def new_path(spark: SparkSession, name: str) -> str:
    path = f"{root(spark)}/{name}-{uuid.uuid4().hex}"
    _written.append((spark, path))
    return path


def kept(df: DataFrame, name: str = "table") -> DataFrame:
    path = new_path(df.sparkSession, name)
    with tidy(df.sparkSession):
        df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def kept_buckets(df: DataFrame, name: str, *keys: str) -> DataFrame:
    """kept, in buckets by keys, so that joins and sums by them move no row of it again."""
    spark, path = df.sparkSession, new_path(df.sparkSession, name)
    table = f"{name}_{uuid.uuid4().hex}"
    with tidy(spark):
        df.write.bucketBy(int(spark.conf.get("spark.sql.shuffle.partitions")), *keys).sortBy(*keys).option("path", path).saveAsTable(table)
    return spark.table(table)


@atexit.register
def _sweep() -> None:
    for spark, path in _written:
        try:
            hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)
        except Exception:  # noqa: BLE001  the session has ended; the folder is the cluster's to clean
            pass
