"""Cutting lineage with written tables in the folder that the whole cluster shares."""

from __future__ import annotations

import gc
import os
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from contextlib import contextmanager
from contextvars import ContextVar
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

PACKAGE = Path(__file__).resolve().parents[1]


def shared_folder(spark: SparkSession) -> str:
    """URI of ``spark.checkpoint.dir``; a temporary folder is set only where none is configured and all tasks run in this process's machine (tests)."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that the whole cluster shares")
        found = "file://" + tempfile.mkdtemp(prefix="assocmine-shared-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    """A path below the shared folder that no other run uses."""
    return f"{shared_folder(spark)}/assocmine/{name}-{uuid.uuid4().hex}"


_collected: ContextVar[list[str] | None] = ContextVar("collected", default=None)


@contextmanager
def collecting(paths: list[str]) -> Iterator[None]:
    """Note the tables that are written inside, so that a caller who is done with them can drop them."""
    before = _collected.set(paths)
    try:
        yield
    finally:
        _collected.reset(before)


def note(path: str) -> None:
    """Leave a table to whoever collects here."""
    if (paths := _collected.get()) is not None:
        paths.append(path)


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back: lineage ends here and survives lost executors."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    note(path)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_path(spark: SparkSession, path: str) -> None:
    """Remove a path of the shared folder through Hadoop's file system API, whatever store it lies in."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def release(spark: SparkSession, paths: list[str]) -> None:
    """Drop tables whose readers are done, and let the driver's collectors find the shuffles behind them, which go with them."""
    while paths:
        drop_path(spark, paths.pop())
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def ship_package(spark: SparkSession) -> None:
    """Send this package to the executors' Python workers, once for each Spark context."""
    sc = spark.sparkContext
    if getattr(sc, "_assocmine_shipped", False):
        return
    archive = os.path.join(tempfile.mkdtemp(prefix="assocmine-code-"), "assocmine_code.zip")
    with zipfile.ZipFile(archive, "w") as out:
        for source in sorted(PACKAGE.rglob("*.py")):
            out.write(source, str(source.relative_to(PACKAGE.parent)))
    sc.addPyFile(archive)
    sc._assocmine_shipped = True
