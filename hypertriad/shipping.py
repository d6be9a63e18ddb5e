"""Puts this package on the executors' path, so that Python functions run where it is not installed."""

from __future__ import annotations

import shutil
import tempfile
from pathlib import Path

from pyspark.sql import SparkSession

_SENT: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send the package once for each application; Spark's own file server hands it to the executors."""
    app = spark.sparkContext.applicationId
    if app in _SENT:
        return
    package = Path(__file__).resolve().parent
    with tempfile.TemporaryDirectory() as tmp:
        copy = shutil.copytree(package, f"{tmp}/src/{package.name}", ignore=shutil.ignore_patterns("__pycache__"))
        made = shutil.make_archive(f"{tempfile.mkdtemp()}/{package.name}", "zip", root_dir=copy.parent if isinstance(copy, Path) else f"{tmp}/src")
    spark.sparkContext.addPyFile(made)
    _SENT.add(app)
