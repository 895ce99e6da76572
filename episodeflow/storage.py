"""The folder that driver and executors share, and plans cut off there."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or the checkpoint folder that was set; where there is neither a temporary one, in local mode only."""
    sc = spark.sparkContext
    at = sc.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not at:
        current = sc._jsc.sc().getCheckpointDir()
        if current.isDefined():
            at = current.get()
        elif sc.master == "local" or sc.master.startswith("local["):
            at = tempfile.mkdtemp(prefix="episodeflow-")
        else:
            raise ValueError("spark.checkpoint.dir has to name a folder that driver and executors share")
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        sc.setCheckpointDir(at)
    return at.rstrip("/")


_given: list[str] = []


def new_path(spark: SparkSession, name: str) -> str:
    """A folder of its own in the shared one."""
    _given.append(f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}")
    return _given[-1]


def remove(spark: SparkSession, path: str) -> None:
    """Remove a folder, if it is there."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def clear(spark: SparkSession) -> None:
    """Remove all folders that new_path has given out: for when the results that read them have been written."""
    while _given:
        remove(spark, _given.pop())


def cut(df: DataFrame) -> DataFrame:
    """The same rows without their lineage: checkpointed, which survives lost executors."""
    shared_dir(df.sparkSession)
    return df.checkpoint()
