"""Ship the package to the executors, whose Python may not find it."""

from __future__ import annotations

import shutil
import tempfile
from pathlib import Path

from pyspark.sql import SparkSession

PACKAGE = Path(__file__).resolve().parents[1]


def ship_package(spark: SparkSession) -> None:
    """Add a zip of the package to the session's context, once."""
    context = spark.sparkContext
    if getattr(context, "_package_shipped", False):
        return
    top = Path(tempfile.mkdtemp(prefix="package-"))
    shutil.copytree(PACKAGE, top / PACKAGE.name, ignore=shutil.ignore_patterns("__pycache__"))
    context.addPyFile(shutil.make_archive(str(top / "shipped"), "zip", top, PACKAGE.name))
    context._package_shipped = True
