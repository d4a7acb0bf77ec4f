"""The session's view of this package."""

from __future__ import annotations

import tempfile
import zipfile
from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor
from pathlib import Path
from typing import Any

from pyspark import SparkContext, inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession

_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Make this package importable by the Python workers of all executors, once for each application."""
    context = spark.sparkContext
    if context.applicationId in _shipped:
        return
    root = Path(__file__).resolve().parent
    archive = Path(tempfile.mkdtemp(prefix="package-")) / f"{root.name}.zip"
    with zipfile.ZipFile(archive, "w") as out:
        for file in sorted(root.rglob("*.py")):
            out.write(file, str(file.relative_to(root.parent)))
    context.addPyFile(str(archive))
    _shipped.add(context.applicationId)


def single_process(spark: SparkSession) -> bool:
    """Whether driver and tasks run in one process, so that a temporary folder is shared by all; local-cluster is no such master."""
    master = spark.sparkContext.master
    return master == "local" or master.startswith("local[")


def shared_folder(spark: SparkSession, purpose: str) -> str:
    """The folder that driver and executors share: the session's checkpoint folder; a temporary one only in a single process."""
    named = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    if not single_process(spark):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and the executors share")
    return tempfile.mkdtemp(prefix=f"{purpose}-")


def checkpoint_folder(spark: SparkSession) -> None:
    """Make sure that the session has a folder for checkpoints."""
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(shared_folder(spark, "checkpoints"))


def kept(df: DataFrame) -> DataFrame:
    """A reliable checkpoint in the session's folder."""
    checkpoint_folder(df.sparkSession)
    return df.checkpoint()


def side_by_side(spark: SparkSession, run: Callable[[Any], Any], items: Iterable[Any], at_once: int) -> list[Any]:
    """run of each item, in the order of the items; the jobs of up to ``at_once`` of them share the cores. Jobs too small to
    fill these by themselves do so together. The caller's job group and tags hold for all; a failure is the caller's."""
    checkpoint_folder(spark)  # set once, before threads would each set their own
    pinned = type(SparkContext._gateway).__name__ == "ClientServer"
    with ThreadPoolExecutor(at_once) as pool:
        return list(pool.map(inheritable_thread_target(spark)(run) if pinned else run, items))
