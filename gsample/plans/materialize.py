"""Lineage cuts that survive the loss of executors.

A cut is a Parquet table in the folder that ``spark.checkpoint.dir`` names, which every
executor of a cluster shares.  Only where that setting is absent (tests, a laptop) a
temporary folder of this machine is used.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable
from contextvars import ContextVar

from pyspark.sql import DataFrame, SparkSession

_own_dir: dict[str, str] = {}
#: Paths of the tables written on the way to a ``distill``ed one.
_on_the_way: ContextVar[list[str] | None] = ContextVar("on_the_way", default=None)


def shared_dir(spark: SparkSession) -> str:
    """The shared folder of this application's tables."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    app = spark.sparkContext.applicationId
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        if app not in _own_dir:
            _own_dir[app] = tempfile.mkdtemp(prefix="gsample-")
        base = _own_dir[app]
    return f"{base.rstrip('/')}/gsample-{app}"


def materialize(df: DataFrame, tag: str = "cut", by: list[str] | None = None) -> DataFrame:
    """Writes ``df`` as Parquet in the shared folder, a folder for each value of ``by``, and returns the table read back."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex[:12]}"
    if _on_the_way.get() is not None:
        _on_the_way.get().append(path)
    (df.write.partitionBy(*by) if by else df.write).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def distill(spark: SparkSession, make: Callable[[], DataFrame], tag: str = "cut") -> DataFrame:
    """Writes what ``make`` returns like ``materialize`` and deletes the tables that were written on the way to it.

    For a ``make`` that hands out nothing else which reads those tables.
    """
    written: list[str] = []
    token = _on_the_way.set(written)
    try:
        df = make()
    finally:
        _on_the_way.reset(token)
    out = materialize(df, tag)
    for path in written:
        _delete(spark, path)
    return out


def release(spark: SparkSession) -> None:
    """Deletes every table that ``materialize`` wrote for this application."""
    _delete(spark, shared_dir(spark))


def _delete(spark: SparkSession, path: str) -> None:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
