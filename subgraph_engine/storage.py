"""Tables that cut lineage: written once to the folder that all executors share.

A written table survives lost executors, is computed exactly once, and gives
every later reader the same rows, which matters for anything that depends on
physical placement (ranks, samples, superstep state).
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_own_root: list[str] = []
#: Paths that the scratch scopes at hand will delete, the innermost last.
_scopes: list[list[str]] = []


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Only a local session without that setting (tests, a laptop) gets a folder of
    its own; on a cluster executors could not read it, so that is an error.
    """
    configured = spark.conf.get("spark.checkpoint.dir", None)
    if configured:
        return configured.rstrip("/")
    if not _is_local(spark.sparkContext.master):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    if not _own_root:
        _own_root.append(tempfile.mkdtemp(prefix="subgraph_engine_"))
    return f"file://{_own_root[0]}"


def _is_local(master: str) -> bool:
    return master == "local" or master.startswith("local[")


def qualified(spark: SparkSession, path: str) -> str:
    """The path with the scheme of the file system that Spark finds it on."""
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(conf).makeQualified(target).toString()


def shared_path(spark: SparkSession, label: str) -> str:
    """A fresh path below the shared folder; it goes with the scratch scope it is made in."""
    path = f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"
    if _scopes:
        _scopes[-1].append(path)
    return path


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Whatever is written below the shared folder in this scope is deleted at its end."""
    _scopes.append([])
    try:
        yield
    finally:
        for path in _scopes.pop():
            drop_path(spark, path)


def only_result(spark: SparkSession, label: str, build: Callable[[], DataFrame]) -> DataFrame:
    """What ``build`` gives, written; all that it has written on its way is deleted."""
    path = shared_path(spark, label)
    with scratch(spark):
        made = build()
        made.write.option("compression", "zstd").parquet(path)
    table = spark.read.schema(made.schema).parquet(path)
    table._shared_path = path
    return table


def written_table(spark: SparkSession, df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` to the shared folder and return a scan of what was written."""
    path = shared_path(spark, label)
    df.write.option("compression", "zstd").parquet(path)
    table = spark.read.schema(df.schema).parquet(path)
    table._shared_path = path
    return table


def release(spark: SparkSession, *tables: DataFrame) -> None:
    """Deletes written tables from which nothing will be read any more."""
    for table in tables:
        if path := getattr(table, "_shared_path", None):
            drop_path(spark, path)


def broadcast_if_few(keys: DataFrame, most: int) -> DataFrame:
    """Marks narrow rows for broadcast when a count shows that they are few; else the join is Spark's choice."""
    return F.broadcast(keys) if keys.limit(most + 1).count() <= most else keys


def drop_path(spark: SparkSession, path: str) -> None:
    """Delete a path below the shared folder, on whatever file system it is."""
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(conf).delete(target, True)


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


#: Bytes of an Arrow batch that carries whole texts.
TEXT_BYTES = "16m"
_BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch"


def text_batches(spark: SparkSession) -> None:
    """Bounds Arrow batches by bytes, in a session that has no bound of its own.

    Batches of ten thousand long texts take hundreds of MB on both sides of the
    socket. The setting is read when a query runs, so it stays with the session.
    """
    if spark.conf.get(_BATCH_BYTES, None) is None:
        spark.conf.set(_BATCH_BYTES, TEXT_BYTES)
