"""Give executors this package, wherever the session was started."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_shipped: set[str] = set()

#: Rows can be whole documents, so batches that go to Python are bounded by bytes (a runtime setting).
BATCH_KEY, BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch", 8 << 20


def ship(spark: SparkSession) -> None:
    """Send the package's source to Python workers once per application.

    Workers that find the package on their own path use that; the archive stands
    behind it. Spark copies the file from the driver, no shared folder is needed.
    """
    context = spark.sparkContext
    if context.applicationId in _shipped:
        return
    size = spark.conf.get(BATCH_KEY)
    if not size.rstrip("b").isdigit() or int(size.rstrip("b")) > BATCH_BYTES:
        spark.conf.set(BATCH_KEY, str(BATCH_BYTES))
    top = Path(__file__).resolve().parent
    if top.is_dir():
        handle, name = tempfile.mkstemp(prefix="twinslot-", suffix=".zip")
        with os.fdopen(handle, "wb") as out, zipfile.ZipFile(out, "w", zipfile.ZIP_DEFLATED) as archive:
            for path in sorted(top.rglob("*.py")):
                archive.write(path, str(path.relative_to(top.parent)))
        context.addPyFile(name)
    _shipped.add(context.applicationId)
