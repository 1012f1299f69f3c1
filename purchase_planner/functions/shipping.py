"""Makes this package importable on executors that do not have it on their path."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_shipped: set[str] = set()


def ship(spark: SparkSession) -> SparkSession:
    """Send the package's sources to the executors, once per application."""
    app = spark.sparkContext.applicationId
    if app not in _shipped:
        root = Path(__file__).resolve().parent.parent
        folder = tempfile.mkdtemp(prefix="planner-code-")  # local masters read it again, so it stays until the end
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        at = f"{folder}/{root.name}.zip"
        with zipfile.ZipFile(at, "w") as z:
            for f in sorted(root.rglob("*.py")):
                z.write(f, f"{root.name}/{f.relative_to(root)}")
        spark.sparkContext.addPyFile(at)
        _shipped.add(app)
    return spark
