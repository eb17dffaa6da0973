"""Gives the executors this package's code, wherever the driver was started."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

PACKAGE = Path(__file__).resolve().parents[1]
_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Add the package to the session's Python files, once for each application."""
    context = spark.sparkContext
    if context.applicationId in _shipped:
        return
    handle, path = tempfile.mkstemp(prefix="distinct_bounds-", suffix=".zip")
    os.close(handle)
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as out:
        for found in sorted(PACKAGE.rglob("*.py")):
            out.write(found, str(found.relative_to(PACKAGE.parent)))
    context.addPyFile(path)
    _shipped.add(context.applicationId)
