"""Arrow functions on executors that don't have this package installed: it is sent along once per Spark context."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import zipfile
from collections.abc import Callable, Iterator
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType

_sent: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send the package's modules to the executors (a few hundred kB)."""
    sc = spark.sparkContext
    if sc.applicationId in _sent:
        return
    package = Path(__file__).resolve().parent
    folder = tempfile.mkdtemp()  # executors may fetch it at any later time
    atexit.register(shutil.rmtree, folder, ignore_errors=True)
    out = Path(folder) / f"{package.name}-{sc.applicationId}.zip"
    with zipfile.ZipFile(out, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(package.rglob("*.py")):
            z.write(p, p.relative_to(package.parent))
    sc.addPyFile(str(out))
    _sent.add(sc.applicationId)


BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"
BATCH_ROWS = 1000  # rows may be whole texts: ten thousand of them in a batch, on both sides, strain an executor


def arrow_map(df: DataFrame, run: Callable, schema: str | StructType) -> DataFrame:
    """mapInArrow with the package at hand. Where the session says nothing of it, batches are set to BATCH_ROWS; their
    bytes are bounded by Spark's own spark.sql.execution.arrow.maxBytesPerBatch."""
    spark = df.sparkSession
    ship(spark)
    if spark.conf.get(BATCH, "-1") == "-1":  # unset
        spark.conf.set(BATCH, str(BATCH_ROWS))
    return df.mapInArrow(run, schema)


def pandas_groups(df: DataFrame, keys: list[str], run: Callable, schema: str | StructType) -> DataFrame:
    ship(df.sparkSession)
    return df.groupBy(*keys).applyInPandas(run, schema)


def arrow_groups(df: DataFrame, keys: list[str], run: Callable, schema: str | StructType) -> DataFrame:
    """A function of one Arrow table, a group's rows."""
    ship(df.sparkSession)
    return df.groupBy(*keys).applyInArrow(run, schema)


def arrow_parts(df: DataFrame, keys: list[str], run: Callable, schema: str | StructType) -> DataFrame:
    """A function of a group's key and its record batches that gives record batches, one by one: a group's result is
    never held as a whole. Its hints tell Spark so."""
    ship(df.sparkSession)

    def parts(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return run(key, batches)

    return df.groupBy(*keys).applyInArrow(parts, schema)
