"""Make the package importable in the executors' Python workers of any session."""

from __future__ import annotations

import functools
import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_shipped: set[str] = set()

ARROW_BYTES, UNBOUNDED = "spark.sql.execution.arrow.maxBytesPerBatch", (1 << 31) - 1
BATCH_BYTES = 64 << 20


def ship(spark: SparkSession) -> None:
    """Send the package to the executors once per application; a later executor fetches it on its first task.

    Also bounds Arrow batches in bytes where the session does not: by rows alone,
    some thousand very long texts would meet in one Python worker.
    """
    if int(spark.conf.get(ARROW_BYTES, str(UNBOUNDED))) >= UNBOUNDED:
        spark.conf.set(ARROW_BYTES, str(BATCH_BYTES))
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    root = Path(__file__).resolve().parent
    target = os.path.join(tempfile.mkdtemp(prefix="semtrie-ship-"), "semtrie_package.zip")
    with zipfile.ZipFile(target, "w") as out:
        for path in sorted(root.rglob("*.py")):
            out.write(path, str(path.relative_to(root.parent)))
    spark.sparkContext.addPyFile(target)
    _shipped.add(app)


def shipped(query):
    """A query (spark, ...) that ships the package first."""

    @functools.wraps(query)
    def run(spark, *args, **kwargs):
        ship(spark)
        return query(spark, *args, **kwargs)

    return run
