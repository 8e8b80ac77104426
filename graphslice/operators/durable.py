"""Tables in the shared folder: they cut lineage and survive lost executors."""

from __future__ import annotations

import atexit
import tempfile
import threading
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; a temporary folder only where none is set (tests)."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = found.get() if found.isDefined() else None
    if not base:
        base = "file://" + tempfile.mkdtemp(prefix="graphslice-")
        spark.sparkContext.setCheckpointDir(base)
    return base


def drop(spark: SparkSession, path: str) -> None:
    try:
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # the session may have ended before
        pass


_thread = threading.local()


@contextmanager
def made():
    """The list of the paths that this thread asks for inside."""
    outer, _thread.made = getattr(_thread, "made", None), []
    try:
        yield _thread.made
    finally:
        _thread.made = outer


@contextmanager
def dropped_after(spark: SparkSession):
    """The tables that this thread writes inside are removed at the end."""
    with made() as paths:
        try:
            yield
        finally:
            for path in paths:
                drop(spark, path)


CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_counted, _depth = threading.Lock(), {}


@contextmanager
def shuffles_dropped(spark: SparkSession):
    """Inside, a query's shuffle files go when the query ends, not when the driver's memory happens to be collected."""
    key = id(spark._jsparkSession)
    with _counted:
        depth, before = _depth.get(key, (0, None))
        if not depth:
            before = spark.conf.get(CLEANUP, None)
            spark.conf.set(CLEANUP, "true")
        _depth[key] = depth + 1, before
    try:
        yield
    finally:
        with _counted:
            depth, before = _depth[key]
            if depth > 1:
                _depth[key] = depth - 1, before
            else:
                del _depth[key]
                spark.conf.unset(CLEANUP) if before is None else spark.conf.set(CLEANUP, before)


def folder(spark: SparkSession, name: str = "t") -> str:
    """A new path in the shared folder, removed when the program ends."""
    path = f"{shared_folder(spark)}/graphslice/{name}-{uuid.uuid4().hex}"
    atexit.register(drop, spark, path)
    if (paths := getattr(_thread, "made", None)) is not None:
        paths.append(path)
    return path


def written(df: DataFrame, name: str = "t", by: str | None = None) -> DataFrame:
    """df written once as Parquet (a folder for each value of `by`) and read back."""
    path = folder(df.sparkSession, name)
    add(df, path, by)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def add(df: DataFrame, path: str, by: str | None = None) -> None:
    out = df.write.mode("append")
    (out.partitionBy(by) if by else out).parquet(path)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))
