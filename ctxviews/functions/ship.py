"""Executors get this package with the first kernel that needs it."""

from __future__ import annotations

import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession


def ship(spark: SparkSession) -> None:
    """Send the package's modules to the executors, once for each application; local workers have them already."""
    sc = spark.sparkContext
    if sc.master.startswith("local[") or getattr(sc, "_ctxviews_core_shipped", False):
        return
    root = Path(__file__).resolve().parents[1]
    path = Path(tempfile.mkdtemp()) / "ctxviews_core.zip"  # read by the driver's own file server
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, str(Path(root.name) / p.relative_to(root)))
    sc.addPyFile(str(path))
    sc._ctxviews_core_shipped = True
