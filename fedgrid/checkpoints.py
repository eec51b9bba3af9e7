"""Reliable lineage cuts: written to the folder that the cluster shares."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def folder(spark: SparkSession) -> str:
    """The folder that the session names in spark.checkpoint.dir.

    Where it names none, a session on one machine (tests) gets one under /tmp; on a cluster that is an error, as no
    folder of one machine outlives its executors.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    context = spark.sparkContext
    if not context.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
    return f"/tmp/checkpoints/{context.applicationId}"


def checkpointed(df: DataFrame) -> DataFrame:
    """``df`` written to that folder, and read from there ever after."""
    context = df.sparkSession.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(folder(df.sparkSession))
    return df.checkpoint(eager=True)


def delete(spark: SparkSession, path: str) -> None:
    """Removes a folder on any file system that Spark writes to."""
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


@contextmanager
def stored(df: DataFrame) -> Iterator[DataFrame]:
    """``df`` as a Parquet table in the shared folder, which is removed at the end of the block: for what is read
    more than once, and is smaller compressed by columns than as a checkpoint."""
    path = f"{folder(df.sparkSession)}/stored-{uuid.uuid4().hex}"
    df.write.parquet(path)
    try:
        yield df.sparkSession.read.parquet(path)
    finally:
        delete(df.sparkSession, path)
