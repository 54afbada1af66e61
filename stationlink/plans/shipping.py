"""Give Python workers this package, wherever the session was started."""

from __future__ import annotations

import os
import tempfile
import zipfile
from functools import wraps
from pathlib import Path

from pyspark.sql import SparkSession

_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Add the package as a zip to the session's files, once for each application."""
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    root = Path(__file__).resolve().parents[1]
    path = os.path.join(tempfile.mkdtemp(prefix="stationlink-"), "stationlink_package.zip")
    with zipfile.ZipFile(path, "w") as archive:
        for f in sorted(root.rglob("*.py")):
            archive.write(f, str(f.relative_to(root.parent)))
    spark.sparkContext.addPyFile(path)
    _SHIPPED.add(app)


def shipped(query):
    """A query (spark, sf_dir) that ships the package first."""

    @wraps(query)
    def run(spark, sf_dir):
        ship(spark)
        return query(spark, sf_dir)

    return run
