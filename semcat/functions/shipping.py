"""Make this package importable in Spark's Python workers, wherever they run."""

from __future__ import annotations

import tempfile
import threading
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_DONE: set[str] = set()
_LOCK = threading.Lock()


def ship(spark: SparkSession) -> None:
    """Send the package's modules to the executors, once for each application."""
    app = spark.sparkContext.applicationId
    with _LOCK:
        if app in _DONE:
            return
        package = Path(__file__).resolve().parent.parent
        target = Path(tempfile.mkdtemp(prefix="semcat-")) / f"{package.name}.zip"
        with zipfile.ZipFile(target, "w") as z:
            for p in sorted(package.rglob("*.py")):
                z.write(p, p.relative_to(package.parent))
        spark.sparkContext.addPyFile(str(target))
        _DONE.add(app)
