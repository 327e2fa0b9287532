"""Session settings and the folder for written intermediates."""

from __future__ import annotations

import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Runtime settings that suit large edge lists; fixed ones are left to the cluster.
SUITABLE = {
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.session.timeZone": "UTC",
}


@contextlib.contextmanager
def settings(spark: SparkSession, **values: str):
    """Runtime settings for the time of a block; the caller's values come back after it."""
    values = {k.replace("__", "."): v for k, v in values.items()}
    before = {k: spark.conf.get(k, None) for k in values}
    for k, v in values.items():
        spark.conf.set(k, v)
    try:
        yield spark
    finally:
        for k, v in before.items():
            if v is None:
                spark.conf.unset(k)
            else:
                spark.conf.set(k, v)


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir where the cluster names one; a local session without it gets a temporary folder."""
    at = spark.conf.get("spark.checkpoint.dir", None)
    if not at:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir: intermediates need a folder that all executors share")
        at = f"{tempfile.gettempdir()}/edgecsr-{spark.sparkContext.applicationId}"
    return at.rstrip("/")


#: A finished write needs its shuffle files no more; Spark drops them at its end instead of at some later collection.
CLEANED = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true"}


def materialize(df: DataFrame, name: str, root: str | None = None) -> DataFrame:
    """Write to the shared folder and read back: row order inside files stays, lineage ends, and so do the shuffle files."""
    spark = df.sparkSession
    path = f"{root or shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    with settings(spark, **CLEANED):
        df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
