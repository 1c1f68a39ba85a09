"""Makes the package importable for Python workers, wherever they run."""

from __future__ import annotations

import io
import os
import tempfile
import threading
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession


_one_at_a_time = threading.Lock()


def ship(spark: SparkSession) -> SparkSession:
    """Send this package to the executors once per application (Spark's own file server)."""
    with _one_at_a_time:
        return _shipped(spark)


def _shipped(spark: SparkSession) -> SparkSession:
    context = spark.sparkContext
    if getattr(context, "_groupmatch_shipped", False):
        return spark
    root = Path(__file__).resolve().parent
    raw = io.BytesIO()
    with zipfile.ZipFile(raw, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, f"{root.name}/{p.relative_to(root)}")
    place = os.path.join(tempfile.mkdtemp(prefix="groupmatch-"), "groupmatch_sources.zip")
    Path(place).write_bytes(raw.getvalue())
    context.addPyFile(place)
    context._groupmatch_shipped = True
    return spark
