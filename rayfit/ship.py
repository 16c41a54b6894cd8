"""Sends the package to executors whose Python does not have it."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_DONE: set[str] = set()


def ship(spark: SparkSession) -> None:
    sc = spark.sparkContext
    if sc.applicationId in _DONE:
        return
    top = Path(__file__).resolve().parents[1]
    to = os.path.join(tempfile.mkdtemp(prefix="rayfit-"), "rayfit_core.zip")
    with zipfile.ZipFile(to, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted((top / "rayfit").rglob("*.py")):
            z.write(p, p.relative_to(top))
    sc.addPyFile(to)
    _DONE.add(sc.applicationId)
