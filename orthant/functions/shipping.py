"""Make the package importable in Python workers, wherever the driver was started."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

PACKAGE = Path(__file__).resolve().parent.parent


def ship(spark: SparkSession) -> None:
    """Add the package to the session's Python files, once for each Spark context."""
    sc = spark.sparkContext
    if getattr(sc, "_orthant_shipped", False):
        return
    folder = tempfile.mkdtemp(prefix="orthant-ship-")
    atexit.register(shutil.rmtree, folder, ignore_errors=True)
    path = Path(folder) / f"{PACKAGE.name}.zip"
    with zipfile.ZipFile(path, "w") as z:
        for source in sorted(PACKAGE.rglob("*.py")):
            z.write(source, source.relative_to(PACKAGE.parent))
    sc.addPyFile(str(path))
    sc._orthant_shipped = True
