"""Sessions: settings for the engine, and the package's way to the executors."""

from __future__ import annotations

import os
import shutil
import tempfile
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def ship(spark: SparkSession) -> None:
    """Give executors this package once per application, so that Python workers can import it."""
    sc = spark.sparkContext
    if getattr(sc, "_trellis_shipped", False):
        return
    root = os.path.dirname(os.path.abspath(__file__))
    folder = tempfile.mkdtemp(prefix="trellis-code-")
    copy = os.path.join(folder, "src", "trellis")
    shutil.copytree(root, copy, ignore=shutil.ignore_patterns("__pycache__"))
    sc.addPyFile(shutil.make_archive(os.path.join(folder, "trellis_code"), "zip", os.path.join(folder, "src")))
    sc._trellis_shipped = True


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder that all machines share; a private one only in local mode."""
    sc = spark.sparkContext
    if not sc.getCheckpointDir():
        shared = sc.getConf().get("spark.checkpoint.dir")
        if not shared and not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="trellis-checkpoint-"))
    return sc.getCheckpointDir()


@contextmanager
def shuffles_freed(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of the jobs within go when their action ends, not when the driver's memory is next collected."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.set(name, before)


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut lineage into the shared folder."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)
