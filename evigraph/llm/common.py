"""Helpers shared by the training-data operators: shared-folder tables, batch slicing, components."""

from __future__ import annotations

import atexit
import contextlib
import os
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BinaryType, DoubleType, IntegerType, LongType, StringType, StructField, StructType

#: Bytes of text that the array kernels take at once; a longer document makes a slice of its own.
SLICE_BYTES = 1_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``; only where none is named (local
    tests) a temporary one is set."""
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not named:
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        named = tempfile.mkdtemp(prefix="evigraph-")
        sc.setCheckpointDir(named)
        named = sc.getCheckpointDir() or named
    return named


def _clear() -> None:
    """Remove the tables of this process, as nothing reads them once it ends."""
    if not _TABLES or os.getpid() != _OWNER:
        return
    with contextlib.suppress(Exception):
        spark = SparkSession.getActiveSession()
        for path in _TABLES if spark is not None else ():
            at = spark._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(at, True)


_TABLES: list[str] = []
_OWNER = os.getpid()
atexit.register(_clear)


def written(df: DataFrame) -> DataFrame:
    """Cut the lineage: write ``df`` as a table into the shared folder and read it back."""
    path = f"{shared_dir(df.sparkSession)}/t-{uuid.uuid4().hex}"
    _TABLES.append(path)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def removed(df: DataFrame) -> None:
    """Delete a table of :func:`written` that nothing reads any more."""
    jvm = df.sparkSession._jvm
    for folder in {f.rpartition("/")[0] for f in df.inputFiles()}:
        path = jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def wrapped(docs: DataFrame, *columns: str) -> DataFrame:
    """All columns of ``docs`` in one struct ``doc``, beside the columns an operator works on, so that no
    column of the input can clash with one that the operator adds."""
    return docs.select(F.struct(*docs.columns).alias("doc"), *columns)


def apart(docs: DataFrame, *columns: str) -> DataFrame:
    """As :func:`wrapped`, but ``text`` stands beside the struct and not in it, so that what goes to a Python
    worker and back holds each text once; :func:`unwrapped` takes it with ``text=F.col("text")``."""
    return docs.select(F.struct(*(c for c in docs.columns if c != "text")).alias("doc"), "text", *columns)


def unwrapped(df: DataFrame, docs: DataFrame, **changed) -> DataFrame:
    """The columns of ``docs`` again, some of them changed."""
    return df.select(*(changed[c].alias(c) if c in changed else F.col("doc").getField(c).alias(c) for c in docs.columns))


def with_fields(docs: DataFrame, drop: tuple[str, ...] = (), **more: str) -> StructType:
    """The schema of ``docs`` without some columns and with more."""
    kept = [f for f in docs.schema.fields if f.name not in drop]
    return StructType([*kept, *(StructField(k, _parse(v)) for k, v in more.items())])


_KINDS = {"long": LongType(), "int": IntegerType(), "double": DoubleType(), "string": StringType(), "binary": BinaryType(), "array<int>": ArrayType(IntegerType()), "array<string>": ArrayType(StringType())}


def _parse(kind: str):
    return _KINDS[kind]


def small(df: DataFrame, rows: int) -> bool:
    """Whether ``df`` has at most ``rows`` rows; reads no more than it must."""
    return df.limit(rows + 1).count() <= rows


def joined_checked(left: DataFrame, right: DataFrame, on: list[str], how: str, rows: int) -> DataFrame:
    """Join that broadcasts the right side only if it has at most ``rows`` rows."""
    return left.join(F.broadcast(right) if small(right, rows) else right, on, how)


def slices(batch: pa.RecordBatch, column: str, most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut a batch into runs of whole rows whose ``column`` has about ``most`` bytes."""
    n = batch.num_rows
    if not n:
        return
    at = offsets(batch.column(column))
    begin = 0
    while begin < n:
        end = int(np.searchsorted(at, at[begin] + most, side="right")) - 1
        end = min(max(end, begin + 1), n)
        yield batch.slice(begin, end - begin)
        begin = end


def offsets(text: pa.Array) -> np.ndarray:
    kind = np.int64 if pa.types.is_large_string(text.type) or pa.types.is_large_binary(text.type) else np.int32
    return np.frombuffer(text.buffers()[1], kind)[text.offset : text.offset + len(text) + 1].astype(np.int64)


def raw(text: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a string column and each row's offsets in them; null counts as empty."""
    if not len(text):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    at = offsets(text)
    data = text.buffers()[2]
    body = np.frombuffer(data, np.uint8)[at[0] : at[-1]] if data is not None else np.zeros(0, np.uint8)
    return body, at - at[0]


def components(nodes_edges: DataFrame, max_rounds: int = 40) -> DataFrame:
    """Connected components of an edge table (a, b): (id, component_id) with the smallest id of each
    component. Each round hooks labels over the edges and halves the label paths; the labels live
    in the shared folder, so no component meets in one task or on the driver. No rows for no edges."""
    both = written(
        nodes_edges.filter("a is not null and b is not null and a <> b").select("a", "b").distinct()
    )
    both = both.unionByName(both.select(F.col("b").alias("a"), F.col("a").alias("b")))
    labels = written(both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("label")).withColumnRenamed("a", "id"))
    for _ in range(max_rounds):
        seen = both.join(labels.select(F.col("id").alias("b"), F.col("label").alias("l")), "b").groupBy("a").agg(F.min("l").alias("l"))
        hooked = labels.join(seen.withColumnRenamed("a", "id"), "id", "left").select(
            "id", F.least("label", F.coalesce("l", "label")).alias("low"), F.col("label").alias("was")
        )
        up = labels.select(F.col("id").alias("low"), F.col("label").alias("above"))
        labels_new = written(
            hooked.join(up, "low", "left").select("id", F.least("low", F.coalesce("above", "low")).alias("label"), "was")
        )
        moved = labels_new.filter("label <> was").limit(1).count()
        labels = labels_new.select("id", "label")
        if not moved:
            return labels.withColumnRenamed("label", "component_id")
    raise RuntimeError("components did not settle; raise max_rounds")
