"""Gives a session's Python workers this package where they can't import it from their own path."""

from __future__ import annotations

import os
import shutil
import tempfile
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = Path(__file__).resolve().parent
_served: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Adds the package to the session's files once, unless PYTHONPATH, which workers inherit, has its folder."""
    app = spark.sparkContext.applicationId
    if app in _served or str(ROOT.parent) in os.environ.get("PYTHONPATH", "").split(os.pathsep):
        return
    _served.add(app)
    with tempfile.TemporaryDirectory() as folder:
        shutil.copytree(ROOT, f"{folder}/src/{ROOT.name}", ignore=shutil.ignore_patterns("__pycache__"))
        target = tempfile.mkdtemp(prefix="motifprune_ship_")
        spark.sparkContext.addPyFile(shutil.make_archive(f"{target}/{ROOT.name}", "zip", f"{folder}/src"))
