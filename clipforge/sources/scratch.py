"""Intermediate tables in the folder that the cluster names in spark.checkpoint.dir."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_LOCAL: list[str] = []
_SCOPES: list[str] = []


def scratch_path(spark: SparkSession, name: str) -> str:
    """A fresh path in the folder that all executors share.

    Where the session names none and runs on this machine alone, a temporary
    folder is made, which goes when the process ends; on a cluster an error is
    raised, for files in an executor's own folder would be missed by the others.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not re.fullmatch(r"local(\[[^,]*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        if not _LOCAL:
            _LOCAL.append(tempfile.mkdtemp(prefix="clipforge-"))
            atexit.register(shutil.rmtree, _LOCAL[0], ignore_errors=True)
        base = _LOCAL[0]
    return "/".join([base.rstrip("/"), *_SCOPES, f"{name}-{uuid.uuid4().hex}"])


def remove(spark: SparkSession, path: str) -> None:
    """Deletes a table or folder, wherever Spark's file systems reach."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


@contextmanager
def scratch_scope(spark: SparkSession) -> Iterator[None]:
    """Intermediate tables made inside go when it ends, so results must have been written elsewhere by then."""
    folder = scratch_path(spark, "scope")
    _SCOPES.append(folder.rsplit("/", 1)[1])
    try:
        yield
    finally:
        _SCOPES.pop()
        remove(spark, folder)


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Writes ``df`` and reads it back, which cuts lineage."""
    path = scratch_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
