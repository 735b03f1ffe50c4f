"""The folder that driver and executors share, and tables kept there."""

from __future__ import annotations

import os
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir, which driver and executors share.  Where it is unset: an own folder without a cluster, else an error."""
    at = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not at and not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    return (at or "/tmp/checkpoints").rstrip("/")


def temp_path(spark: SparkSession, what: str) -> str:
    return f"{shared_folder(spark)}/{what}-{os.urandom(8).hex()}"


_KEPT: list[str] = []


def clear_kept(spark: SparkSession) -> None:
    """Deletes all tables that this driver has kept so far; frames that read them are void then."""
    for path in [*_KEPT]:
        drop_kept(spark, path)


def drop_kept(spark: SparkSession, path: str) -> None:
    """Deletes one kept table that nothing reads any more."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
    _KEPT.remove(path)


@contextmanager
def shuffles_removed(spark: SparkSession, key: str = "spark.sql.classic.shuffleDependency.fileCleanup.enabled") -> Iterator[None]:
    """Each query inside leaves no shuffle files once it has ended; else they stay until the driver happens to collect its garbage."""
    was = spark.conf.get(key, None)
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.unset(key) if was is None else spark.conf.set(key, was)


def keep(df: DataFrame, what: str, paths: list[str] | None = None) -> DataFrame:
    """Written once in the shared folder and read back: cuts the lineage, and fixes which partition a row was in.  Its place is added to `paths`."""
    spark, schema = df.sparkSession, df.schema
    path = temp_path(spark, what)
    df.write.parquet(path)
    _KEPT.append(path)
    if paths is not None:
        paths.append(path)
    return spark.read.schema(schema).parquet(path)
