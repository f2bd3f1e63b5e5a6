"""What a session needs: this package at the Python workers, batches of bounded size, no shuffle files of finished jobs; and rows by key."""

from __future__ import annotations

import os
import tempfile
import zipfile
from collections.abc import Iterator
from pathlib import Path

import pyarrow as pa
from pyspark.sql import SparkSession

_shipped: set[str] = set()
#: Bytes of an Arrow batch that goes to a Python worker, where the session has Spark's default of 64 MB: rows may be long.
ARROW_BATCH, _BYTES = "8MB", "spark.sql.execution.arrow.maxBytesPerBatch"
#: Spark deletes an execution's shuffle files at its end, not when the driver collects garbage: loops of many jobs hold those of one.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def ship(spark: SparkSession) -> SparkSession:
    """Send the package to the executors once per application, as a zip that Spark's file server hands out; bound Arrow batches, and the life of shuffle files."""
    context = spark.sparkContext
    if spark.conf.get(_BYTES, None) in ("67108864b", "64MB"):
        spark.conf.set(_BYTES, ARROW_BATCH)
    spark.conf.set(_CLEANUP, "true")
    if context.applicationId not in _shipped:
        here = Path(__file__).resolve().parent
        to = os.path.join(tempfile.mkdtemp(prefix="bipercolate-zip-"), "bipercolate.zip")
        with zipfile.ZipFile(to, "w", zipfile.ZIP_DEFLATED) as archive:
            for file in sorted(here.rglob("*.py")):
                archive.write(file, str(file.relative_to(here.parent)))
        context.addPyFile(to)
        _shipped.add(context.applicationId)
    return spark


def consecutive(batches: Iterator[pa.RecordBatch], key: str) -> Iterator[list[dict]]:
    """Rows of one key after another, from batches sorted by it: a worker holds one key's rows at a time."""
    rows: list[dict] = []
    for batch in batches:
        for row in batch.to_pylist():
            if rows and rows[0][key] != row[key]:
                yield rows
                rows = []
            rows.append(row)
    if rows:
        yield rows
