"""Hands the package to the executors, for sessions started without it on their path."""

from __future__ import annotations

import shutil
import tempfile
from pathlib import Path

from pyspark.sql import SparkSession

_sent: set[str] = set()


def ship(spark: SparkSession) -> SparkSession:
    """Add this package to the session's Python files, once per application; the driver serves the archive."""
    app = spark.sparkContext.applicationId
    if app not in _sent:
        root = Path(__file__).resolve().parent.parent
        folder = tempfile.mkdtemp(prefix="componentry-")
        spark.sparkContext.addPyFile(shutil.make_archive(f"{folder}/componentry", "zip", root.parent, root.name))
        _sent.add(app)
    return spark
