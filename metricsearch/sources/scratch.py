"""Tables an operator needs more than once, written to the folder all executors share."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_SETTING = "spark.checkpoint.dir"
_written: dict[str, list[str]] = {}


def scratch_root(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; where that is unset (tests on one machine), a temporary one."""
    root = spark.conf.get(_SETTING, None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError(f"set {_SETTING} to a folder that the driver and all executors share")
        root = _written.setdefault("", [f"file://{tempfile.mkdtemp(prefix="scratch-")}"])[0]
    spark.sparkContext.setCheckpointDir(root) if not spark.sparkContext.getCheckpointDir() else None
    return root.rstrip("/")


def _fs(spark: SparkSession, path: str):
    jvm_path = spark._jvm.org.apache.hadoop.fs.Path(path)
    return jvm_path.getFileSystem(spark._jsc.hadoopConfiguration()), jvm_path


def delete(spark: SparkSession, path: str) -> None:
    fs, jvm_path = _fs(spark, path)
    fs.delete(jvm_path, True)


def new_path(spark: SparkSession, name: str, owner: str = "query") -> str:
    """A fresh path under the shared folder, remembered under ``owner`` for :func:`release`."""
    path = f"{scratch_root(spark)}/{name}-{uuid.uuid4().hex}"
    fs, jvm_path = _fs(spark, path)
    fs.deleteOnExit(jvm_path)  # whatever the store, if nobody releases it before
    _written.setdefault(owner, []).append(path)
    return path


def write_table(df: DataFrame, name: str, owner: str = "query", form: str = "parquet", **options) -> DataFrame:
    """Write ``df`` once and return the table read back; this also cuts the lineage, so lost executors cost little."""
    spark = df.sparkSession
    path = new_path(spark, name, owner)
    df.write.format(form).options(**options).save(path)
    return spark.read.schema(df.schema).format(form).load(path)


@contextmanager
def small_batches(spark: SparkSession, rows: int = 1000, size: int = 4 << 20) -> Iterator[None]:
    """While it holds, plans that run send Python batches of at most ``rows`` rows and ``size`` bytes: for rows that
    carry sets or lists, whose number says little about their memory."""
    with _held(spark, {"spark.sql.execution.arrow.maxRecordsPerBatch": str(rows), "spark.sql.execution.arrow.maxBytesPerBatch": str(size)}):
        yield


@contextmanager
def freed_shuffles(spark: SparkSession) -> Iterator[None]:
    """While it holds, the shuffle files of a query go when it ends, not when the driver happens to collect garbage: for
    queries that read written tables, not each other's shuffles."""
    with _held(spark, {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true"}):
        yield


@contextmanager
def _held(spark: SparkSession, own: dict[str, str]) -> Iterator[None]:
    before = {k: spark.conf.get(k, None) for k in own}
    for k, v in own.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.set(k, v) if v is not None else spark.conf.unset(k)


def small_side(df: DataFrame, most_rows: int = 500_000) -> DataFrame:
    """``df`` with a broadcast hint if it has at most ``most_rows`` narrow rows, else as it is: a shuffled join."""
    return F.broadcast(df) if df.limit(most_rows + 1).count() <= most_rows else df


def release(spark: SparkSession, owner: str) -> None:
    """Delete what ``owner`` and its parts (``owner/...``) have written; call it only when no lazy DataFrame reads it."""
    for name in [x for x in _written if x and (x == owner or x.startswith(f"{owner}/"))]:
        for path in _written.pop(name):
            fs, jvm_path = _fs(spark, path)
            fs.delete(jvm_path, True)
            fs.cancelDeleteOnExit(jvm_path)


def deal_by_range(df: DataFrame, *keys: str | Column, part_bytes: int = 64 << 20) -> DataFrame:
    """``df`` dealt by ranges of ``keys``: where its files are larger than ``spark.sql.shuffle.partitions`` parts of
    ``part_bytes``, into as many more; else as the session says, so that parts may still be put together."""
    size = int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    parts = -(-size // part_bytes) if size < 1 << 60 else 0  # beyond: unknown
    usual = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return df.repartitionByRange(parts, *keys) if usual < parts else df.repartitionByRange(*keys)


@atexit.register
def _drop_local() -> None:
    """At the end of the driver's process, tables in folders that it can reach itself go, without the JVM too."""
    import shutil

    for path in [p for paths in _written.values() for p in paths]:
        shutil.rmtree(path.removeprefix("file://"), ignore_errors=True)
