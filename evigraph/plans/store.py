"""Tables in the folder that all executors share."""

from __future__ import annotations

import atexit
import contextlib
import os
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; a temporary folder only in local mode where none is named."""
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not named:
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="evigraph-"))
        named = sc.getCheckpointDir()
    return named


def path_for(spark: SparkSession, name: str) -> str:
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    if _PASSING:
        _PASSING[-1].append(path)
    return path


def _remove(spark: SparkSession, paths: list[str]) -> None:
    for path in paths:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(at, True)


def _clear() -> None:
    """Remove the tables of this process, as nothing reads them once it ends."""
    if not _TABLES or os.getpid() != _OWNER:
        return
    with contextlib.suppress(Exception):
        spark = SparkSession.getActiveSession()
        if spark is not None:
            _remove(spark, _TABLES)


_TABLES: list[str] = []
_PASSING: list[list[str]] = []
_OWNER = os.getpid()
atexit.register(_clear)

#: Source rows that one part of a job may take that is done part by part.
PART_ROWS = 4_000_000
#: Whether an execution's shuffle files go when it ends, and not when the driver collects its garbage.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextlib.contextmanager
def passing(spark: SparkSession) -> Iterator[None]:
    """For one part of a job: what is written inside, tables and packs, goes at its end, and files of a shuffle
    go with the execution that made them. What outlives the part is written to a path made before it."""
    was = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    _PASSING.append([])
    try:
        yield
    finally:
        own = _PASSING.pop()
        spark.conf.unset(CLEANUP) if was is None else spark.conf.set(CLEANUP, was)
        _remove(spark, own)
        _TABLES[:] = [path for path in _TABLES if path not in own]


def written(df: DataFrame, codec: str = "snappy") -> DataFrame:
    path = path_for(df.sparkSession, "table")
    _TABLES.append(path)
    df.write.option("compression", codec).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def appended(df: DataFrame, path: str) -> None:
    """Rows added to a table of this process that is written part by part."""
    if path not in _TABLES:
        _TABLES.append(path)
    df.write.mode("append").parquet(path)


def bounded(df: DataFrame, rows: int = 2_000_000) -> DataFrame:
    """``df`` to be broadcast if it has at most ``rows`` rows, which must be narrow, else as it is."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df
