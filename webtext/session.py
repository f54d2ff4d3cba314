"""Sessions: one for tests and benches, and what any given session needs to run this package's Python code."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_HERE = Path(__file__).resolve().parent


def local(cores: int | str = "*", partitions: int = 8) -> SparkSession:
    """A local session. Reuses a running one; never changes what is fixed at start."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", os.environ.get("WEBTEXT_DRIVER_MEMORY", "8g"))
        .getOrCreate()
    )


def ship(spark: SparkSession) -> SparkSession:
    """Makes this package importable on the executors, whatever folder the driver was started in."""
    sc = spark.sparkContext
    if getattr(sc, "_webtext_shipped", False):
        return spark
    folder = tempfile.mkdtemp(prefix="webtext-code-")
    path = os.path.join(folder, "webtext_code.zip")
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as out:
        for f in sorted(_HERE.rglob("*.py")):
            out.write(f, Path("webtext") / f.relative_to(_HERE))
    sc.addPyFile(path)
    sc._webtext_shipped = True
    return spark
