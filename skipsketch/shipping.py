"""Makes this package importable by Python workers of a session that was started without it."""

from __future__ import annotations

import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

#: A setting that may change at any time; one that the user has chosen stays.
BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"
_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Give the package's sources to the workers, once for each application."""
    context = spark.sparkContext
    if spark.conf.get(BATCH) == "10000":  # the default; of long texts so many rows are too much memory at once
        spark.conf.set(BATCH, "1000")
    if context.applicationId in _shipped:
        return
    top = Path(__file__).resolve().parent
    archive = Path(tempfile.mkdtemp()) / "skipsketch_sources.zip"
    with zipfile.ZipFile(archive, "w", zipfile.ZIP_DEFLATED) as z:
        for source in sorted(top.rglob("*.py")):
            z.write(source, source.relative_to(top.parent))
    context.addPyFile(str(archive))
    _shipped.add(context.applicationId)
