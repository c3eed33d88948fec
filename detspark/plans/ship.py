"""Make the package importable for Python workers of a session that was started elsewhere."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_ROOT = Path(__file__).resolve().parents[2]


def ship(spark: SparkSession) -> SparkSession:
    """Send the package to the executors once per context, unless their path already holds it."""
    context = spark.sparkContext
    on_path = str(_ROOT) in [str(Path(p).resolve()) for p in os.environ.get("PYTHONPATH", "").split(os.pathsep) if p]
    if on_path or getattr(context, "_detspark_shipped", False):
        return spark
    target = Path(tempfile.mkdtemp(prefix="detspark-code-")) / "detspark_code.zip"
    with zipfile.ZipFile(target, "w") as archive:
        for source in sorted((_ROOT / "detspark").rglob("*.py")):
            archive.write(source, source.relative_to(_ROOT))
    context.addPyFile(str(target))
    context._detspark_shipped = True
    return spark
