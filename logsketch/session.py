"""The session as it is given: nothing here changes settings that are fixed at start."""

from __future__ import annotations

import os
import tempfile
import zipfile

from pyspark.sql import SparkSession

_shipped: set[str] = set()


def ship(spark: SparkSession) -> SparkSession:
    """Lets Python workers import this package, whatever path they were started with (once per application)."""
    sc = spark.sparkContext
    if sc.applicationId not in _shipped:
        top = os.path.dirname(os.path.abspath(__file__))
        path = os.path.join(tempfile.mkdtemp(), "logsketch.zip")
        with zipfile.ZipFile(path, "w") as z:
            for folder, _, names in os.walk(top):
                for name in names:
                    if name.endswith(".py"):
                        z.write(full := os.path.join(folder, name), os.path.relpath(full, os.path.dirname(top)))
        sc.addPyFile(path)
        _shipped.add(sc.applicationId)
    return spark


def session(app: str = "logsketch", partitions: int | None = None) -> SparkSession:
    """A session for tests and notebooks; a cluster's own session is used as it is."""
    builder = SparkSession.builder.appName(app).config("spark.sql.session.timeZone", "UTC").config("spark.sql.execution.arrow.pyspark.enabled", "true")
    if partitions:
        builder = builder.config("spark.sql.shuffle.partitions", str(partitions))
    return ship(builder.getOrCreate())
