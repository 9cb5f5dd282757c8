"""Shared storage for intermediate tables and binary files.

Everything an executor writes for another one goes below the folder that the session names in
``spark.checkpoint.dir``; only where that is unset (tests) is a folder of this machine used.
"""

from __future__ import annotations

import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_LOCAL: dict[str, str] = {}
#: Tables of the open `scratch` blocks, the innermost last.
_MADE: list[list[str]] = []


def shared_root(spark: SparkSession) -> str:
    """The shared folder of this session."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    master = spark.sparkContext.master
    if master != "local" and not master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    app = spark.sparkContext.applicationId
    if app not in _LOCAL:
        _LOCAL[app] = "file://" + tempfile.mkdtemp(prefix="treecount-")
    return _LOCAL[app]


def fresh_path(spark: SparkSession, name: str) -> str:
    """A path below the shared folder that no other call gets."""
    return f"{shared_root(spark)}/llm-{name}-{uuid.uuid4().hex[:12]}"


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` as a table in the shared folder, read again: it survives lost executors and cuts lineage."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._store_path = path
    if _MADE:
        _MADE[-1].append(path)
    return out


@contextmanager
def scratch(spark: SparkSession) -> Iterator[Callable[[DataFrame], DataFrame]]:
    """Delete the tables that the block made, but for those handed to what it yields; shuffle files go with them."""
    kept: list[str] = []

    def keep(df: DataFrame) -> DataFrame:
        kept.append(df._store_path)
        return df

    _MADE.append([])
    try:
        yield keep
    finally:
        made = _MADE.pop()
        for path in made:
            if path not in kept:
                delete(spark, path)
        if _MADE:
            _MADE[-1].extend(p for p in made if p in kept)
    release(spark)


def forget(df: DataFrame) -> None:
    """Delete a table made by `written` that nothing reads any more."""
    path = getattr(df, "_store_path", None)
    if path:
        delete(df.sparkSession, path)


def delete(spark: SparkSession, path: str) -> None:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def release(spark: SparkSession) -> None:
    """Let Spark's cleaner drop the shuffle files of finished jobs now, not when the driver next collects garbage."""
    gc.collect()
    spark._jvm.System.gc()


def small_batches(spark: SparkSession, rows: int = 512) -> None:
    """Bound the rows of one Arrow batch, so that a batch of long texts fits a Python worker."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(key, "10000"))
    if now <= 0 or now > rows:
        spark.conf.set(key, str(rows))


def open_file_system(uri: str):
    """(pyarrow file system, path in it) of a URI; used on executors."""
    from pyarrow import fs

    if "://" not in uri and uri.startswith("file:"):
        uri = "file://" + uri[5:]
    return fs.FileSystem.from_uri(uri)
