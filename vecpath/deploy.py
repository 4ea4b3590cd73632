"""Make the package importable on executors."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_sent: set[str] = set()
BATCHES = "spark.sql.execution.arrow.maxBytesPerBatch"
BATCH_BYTES = 8 << 20


def ship_package(spark: SparkSession) -> None:
    """Send the package's sources to the executors, once per application.

    Arrow batches of the session get at most ``BATCH_BYTES``, so that long
    texts do not fill the workers' memory; a lower bound of the user stays.
    """
    held = str(spark.conf.get(BATCHES, "64m"))
    if not held.rstrip("b").isdigit() or int(held.rstrip("b")) > BATCH_BYTES or int(held.rstrip("b")) <= 0:
        spark.conf.set(BATCHES, str(BATCH_BYTES))
    app = spark.sparkContext.applicationId
    if app in _sent:
        return
    root = Path(__file__).resolve().parent
    target = os.path.join(tempfile.mkdtemp(prefix="vecpath-"), "vecpath_sources.zip")
    with zipfile.ZipFile(target, "w") as z:
        for path in sorted(root.rglob("*.py")):
            z.write(path, str(path.relative_to(root.parent)))
    spark.sparkContext.addPyFile(target)
    _sent.add(app)
