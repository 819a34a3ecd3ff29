"""Shared storage: where tables that cut lineage are written, and how they go again."""

from __future__ import annotations

import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Folders written since the last ``drop_kept``.
_written: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder named by ``spark.checkpoint.dir``.

    Where none is named, a temporary one on a local master (tests); on a cluster that would lie on one
    machine alone, so it is refused.
    """
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        where = getattr(shared_dir, "own", None) or tempfile.mkdtemp(prefix="shared-")
        shared_dir.own = where
    return where


def new_path(spark: SparkSession, name: str) -> str:
    path = f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    _written.append(path)
    return path


def kept(df: DataFrame, name: str, compression: str | None = None) -> DataFrame:
    """``df`` written once to the shared folder and read back."""
    path = new_path(df.sparkSession, name)
    writer = df.write.option("compression", compression) if compression else df.write
    writer.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._kept_at = path
    return out


def _delete(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def discard(*frames: DataFrame) -> None:
    """Delete kept tables that nothing reads any more."""
    for df in frames:
        path = getattr(df, "_kept_at", None)
        if path:
            _delete(df.sparkSession, path)
            with contextlib.suppress(ValueError):
                _written.remove(path)


def drop_kept(spark: SparkSession) -> int:
    """Delete all that was kept since the last call; results that still read it must be written first."""
    gone = len(_written)
    while _written:
        _delete(spark, _written.pop())
    return gone
