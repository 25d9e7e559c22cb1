"""Folders that driver and executors share, and tables written there to cut lineage."""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_written: list[tuple[SparkSession, str]] = []


_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Let Python workers import this package, whatever their path; once for each application."""
    application = spark.sparkContext.applicationId
    if application not in _shipped:
        _shipped.add(application)
        root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
        folder = tempfile.mkdtemp(prefix="phrasework-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        spark.sparkContext.addPyFile(shutil.make_archive(f"{folder}/phrasework", "zip", root, "phrasework"))


def shared_dir(spark: SparkSession) -> str:
    """The folder named by ``spark.checkpoint.dir``.

    Where that is unset, the folder set for checkpoints; else on a cluster one in the warehouse, which all
    machines see, and a temporary one where driver and executors are one process.
    """
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder is None:
        current = spark.sparkContext.getCheckpointDir()
        if current is None:
            local = spark.sparkContext.master.startswith("local")
            current = f"{tempfile.gettempdir() if local else spark.conf.get('spark.sql.warehouse.dir')}/phrasework-shared"
            spark.sparkContext.setCheckpointDir(current)
        folder = current
    return folder.rstrip("/")


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder through Hadoop's file system, wherever it lies."""
    jvm = spark.sparkContext._jvm
    hadoop_path = jvm.org.apache.hadoop.fs.Path(path)
    hadoop_path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop_path, True)


def remove_all() -> None:
    """Delete all materialised tables; runs by itself when Python ends, too late for a stopped session."""
    for spark, path in _written:
        try:
            remove(spark, path)
        except Exception:  # the session may be gone by now
            pass
    _written.clear()


atexit.register(remove_all)


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back.

    Later readers neither recompute ``df`` nor depend on an executor staying alive. The
    folder goes when the Python process ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    _written.append((spark, path))
    df.write.parquet(path)
    table = spark.read.schema(df.schema).parquet(path)
    table._materialized_at = path
    return table


def own_path(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder that goes when the Python process ends, as materialised tables do."""
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    _written.append((spark, path))
    return path


def release(*tables: DataFrame) -> None:
    """Delete materialised tables that nothing reads any more, later lazy reads included."""
    for table in tables:
        spark, path = table.sparkSession, table._materialized_at
        remove(spark, path)
        _written.remove((spark, path))
