"""Sends this package to the executors once per application."""

from __future__ import annotations

import os
import tempfile
import zipfile

from pyspark.sql import SparkSession

_sent: set[str] = set()
BATCH = "spark.sql.execution.arrow.maxBytesPerBatch"


def ship(spark: SparkSession) -> None:
    """Adds the package's sources to the Python path of every worker, also of those that start later."""
    app = spark.sparkContext.applicationId
    if app in _sent:
        return
    _sent.add(app)
    if spark.conf.get(BATCH, None) in (None, "64MB", str(64 << 20), str((1 << 63) - 1)):
        spark.conf.set(BATCH, "8MB")  # long texts: rows per batch alone would not bound a batch
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    path = os.path.join(tempfile.mkdtemp(prefix="gsample-src-"), "gsample_src.zip")
    with zipfile.ZipFile(path, "w") as z:
        for folder, _, names in os.walk(root):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(folder, name)
                    z.write(full, os.path.join("gsample", os.path.relpath(full, root)))
    spark.sparkContext.addPyFile(path)
