"""Sends the package to executors whose Python cannot import it."""

from __future__ import annotations

import shutil
import tempfile
from pathlib import Path

from pyspark.sql import SparkSession

_SENT: set[str] = set()


def ship_package(spark: SparkSession) -> None:
    """Adds a zip of this package to the application's Python files, once."""
    app = spark.sparkContext.applicationId
    if app in _SENT:
        return
    root = Path(__file__).resolve().parents[1]
    folder = tempfile.mkdtemp(prefix="motifmill-")
    zipped = shutil.make_archive(f"{folder}/motifmill", "zip", root_dir=root.parent, base_dir=root.name)
    spark.sparkContext.addPyFile(zipped)
    _SENT.add(app)
