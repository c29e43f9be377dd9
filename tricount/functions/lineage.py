"""Cutting lineage in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def ensure_folder(spark: SparkSession) -> None:
    """Gives the context its checkpoint folder: the session's spark.checkpoint.dir. Where that is unset, a temporary one if everything runs on this machine, as in tests; a cluster must name one."""
    context = spark.sparkContext
    if context.getCheckpointDir():
        return
    there = spark.conf.get("spark.checkpoint.dir", None)
    if not there and not context.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    context.setCheckpointDir(there or tempfile.mkdtemp(prefix="tricount-"))


def checkpointed(df: DataFrame) -> DataFrame:
    """The rows as computed once, whatever happens to an executor later; partitions and their order stay."""
    ensure_folder(df.sparkSession)
    return df.checkpoint()


def written(df: DataFrame) -> DataFrame:
    """The rows written as parquet to the shared folder and read again: a fraction of what a checkpoint takes, which writes rows as they are. What their plan shuffled may go; the driver is asked to let go of it."""
    spark = df.sparkSession
    ensure_folder(spark)
    path = f"{spark.conf.get('spark.checkpoint.dir', None) or spark.sparkContext.getCheckpointDir()}/rows-{uuid.uuid4().hex}"
    df.write.parquet(path)
    spark.sparkContext._jvm.System.gc()  # shuffle files of plans that nothing holds are removed after a collection
    out = spark.read.schema(df.schema).parquet(path)
    out._is_written = True
    return out


def once(df: DataFrame) -> DataFrame:
    """The rows written, if they are not already."""
    return df if getattr(df, "_is_written", False) else written(df)
