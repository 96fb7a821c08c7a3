"""Sending this package to the executors."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send this package to the executors once per application, so Python workers can import it."""
    sc = spark.sparkContext
    if sc.applicationId in _SHIPPED:
        return
    root = Path(__file__).resolve().parents[1]
    folder = tempfile.mkdtemp(prefix="evenlane-")  # the driver's own: Spark sends the file on
    atexit.register(shutil.rmtree, folder, True)
    target = Path(folder) / "evenlane_pkg.zip"
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted((root / "evenlane").rglob("*.py")):
            z.write(p, p.relative_to(root))
    sc.addPyFile(str(target))
    _SHIPPED.add(sc.applicationId)
