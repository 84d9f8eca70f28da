"""Makes this package importable by Python workers that do not share the driver's import path."""

from __future__ import annotations

import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Sends the package's sources to the executors, once per application."""
    sc = spark.sparkContext
    if sc.applicationId in _shipped:
        return
    _shipped.add(sc.applicationId)
    home = Path(__file__).resolve().parent
    if home.suffix or not home.is_dir():  # already imported from an archive
        return
    path = f"{tempfile.mkdtemp()}/{home.name}.zip"
    with zipfile.ZipFile(path, "w") as z:
        for source in sorted(home.rglob("*.py")):
            z.write(source, source.relative_to(home.parent))
    sc.addPyFile(path)
