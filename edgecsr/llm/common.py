"""Helpers shared by the text operators."""

from __future__ import annotations

import ctypes
import gc
import sys
import types
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgecsr.session import materialize, shared_dir

__all__ = ["Scratch", "documents_only", "fresh", "materialize", "per_worker", "read", "release", "shared_dir"]


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


class Scratch:
    """Written intermediates of one operator, deleted together once its result is written."""

    def __init__(self, spark: SparkSession):
        self.spark, self.root = spark, f"{shared_dir(spark)}/scratch-{uuid.uuid4().hex}"

    def keep(self, df: DataFrame, name: str) -> DataFrame:
        return materialize(df, name, self.root)

    def _delete(self, path: str) -> None:
        """Without a JVM at hand it stays."""
        jvm = getattr(self.spark, "_jvm", None)
        if jvm is not None:
            path = jvm.org.apache.hadoop.fs.Path(path)
            system = path.getFileSystem(self.spark._jsc.hadoopConfiguration())
            for found in system.globStatus(path) or []:
                system.delete(found.getPath(), True)

    def forget(self, *names: str) -> None:
        """Deletes what was kept under these names; nothing that is still to run may read it."""
        for name in names:
            self._delete(f"{self.root}/{name}-*")

    def drop(self) -> None:
        """Deletes all; call it when nothing that is still to run reads an intermediate."""
        self._delete(self.root)


def release(spark: SparkSession) -> None:
    """Gives back what ended jobs and fits have left on the driver.

    Spark drops broadcasts, there and on the executors, when the driver's JVM finds that nothing refers to
    them; a driver that plans many small jobs grows its heap instead, and Python keeps freed memory.
    """
    gc.collect()
    jvm = getattr(spark, "_jvm", None)
    if jvm is not None:
        jvm.System.gc()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None) if sys.platform == "linux" else None
    if trim is not None:  # other C libraries have none
        trim(0)


def documents_only(docs: DataFrame) -> DataFrame:
    """Key and text alone; further columns, whatever their names, take no part."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def fresh(taken: list[str], n: int) -> list[str]:
    """``n`` column names that none of ``taken`` has, in any case."""
    used, out = {c.lower() for c in taken}, []
    for i in range(n):
        name = f"in{i}"
        while name in used:
            name += "_"
        out.append(name)
    return out


def per_worker(key, make):
    """``make()``, kept in this Python worker for its later tasks; only for values that depend on the key alone."""
    kept = sys.modules.setdefault("_edgecsr_worker", types.ModuleType("_edgecsr_worker")).__dict__
    if key not in kept:
        kept[key] = make()
    return kept[key]
