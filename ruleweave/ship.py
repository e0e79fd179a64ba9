"""Gives the executors this package, so that Python workers find it whatever their own path is."""

from __future__ import annotations

import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_DONE: set[str] = set()


def ship(spark: SparkSession) -> SparkSession:
    """Adds a zip of the package to the session's files, once an application."""
    app = spark.sparkContext.applicationId
    if app not in _DONE:
        top = Path(__file__).resolve().parent
        target = Path(tempfile.mkdtemp(prefix="ruleweave-")) / "ruleweave_code.zip"
        with zipfile.ZipFile(target, "w") as z:
            for p in sorted(top.rglob("*.py")):
                z.write(p, p.relative_to(top.parent))
        spark.sparkContext.addPyFile(str(target))
        _DONE.add(app)
    return spark
