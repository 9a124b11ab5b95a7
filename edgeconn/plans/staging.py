"""Intermediate tables in the folder that driver and executors share.

A staged table cuts lineage: a lost executor costs a re-read of Parquet files,
never a rerun of the steps before. The folder is the session's
``spark.checkpoint.dir``; only where that is unset on a local master (tests) a
folder of our own is used, on a cluster that is an error.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

LOCAL_FALLBACK = "/tmp/checkpoints"


def shared_dir(spark: SparkSession) -> str:
    """The shared folder for staged tables and checkpoints of this session."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    if not path:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        path = LOCAL_FALLBACK
        spark.sparkContext.setCheckpointDir(path)
    return path.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    path = f"{shared_dir(spark)}/edgeconn-{name}-{uuid.uuid4().hex[:12]}"
    _MADE.append(path)
    return path


def remove(spark: SparkSession, path: str) -> None:
    """Delete a staged path through Hadoop's file system API."""
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


_MADE: list[str] = []


def clear(spark: SparkSession) -> int:
    """Delete what this process has staged; results that read it must have
    been written by then."""
    n = len(_MADE)
    while _MADE:
        remove(spark, _MADE.pop())
    return n


@dataclass(frozen=True)
class Staged:
    """A written intermediate table."""

    spark: SparkSession
    path: str

    @property
    def df(self) -> DataFrame:
        return self.spark.read.parquet(self.path)

    def drop(self) -> None:
        remove(self.spark, self.path)


def stage(df: DataFrame, name: str) -> Staged:
    """Write ``df`` once to the shared folder and hand back a reader of it."""
    spark = df.sparkSession
    out = Staged(spark, new_path(spark, name))
    df.write.mode("overwrite").parquet(out.path)
    return out
