"""Make this package importable for Python workers on every executor."""

from __future__ import annotations

import os
import tempfile
import zipfile

from pyspark.sql import SparkSession

PACKAGE = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def ship(spark: SparkSession) -> SparkSession:
    """Send the package's source to the executors once for each Spark application; Spark's own file server carries it."""
    sc = spark.sparkContext
    if getattr(sc, "_clusterfuse_shipped", False):
        return spark
    path = os.path.join(tempfile.mkdtemp(), "clusterfuse_source.zip")
    with zipfile.ZipFile(path, "w") as out:
        for folder, _, names in os.walk(PACKAGE):
            for name in sorted(names):
                if name.endswith(".py"):
                    full = os.path.join(folder, name)
                    out.write(full, os.path.join(os.path.basename(PACKAGE), os.path.relpath(full, PACKAGE)))
    sc.addPyFile(path)
    sc._clusterfuse_shipped = True
    return spark
