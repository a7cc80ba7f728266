"""Makes the package importable in Python workers."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = Path(__file__).resolve().parents[2]


def ship(spark: SparkSession) -> None:
    """Sends the package to the executors as a zip file, unless their search path has it already; once a context."""
    context = spark.sparkContext
    here = {os.path.realpath(p) for p in (*os.environ.get("PYTHONPATH", "").split(os.pathsep), os.getcwd()) if p}
    if str(ROOT) in here or getattr(context, "_ldpspark_shipped", False):
        return
    path = Path(tempfile.mkdtemp()) / "ldpspark.zip"
    with zipfile.ZipFile(path, "w") as z:
        for f in (ROOT / "ldpspark").rglob("*.py"):
            z.write(f, f.relative_to(ROOT))
    context.addPyFile(str(path))
    context._ldpspark_shipped = True
