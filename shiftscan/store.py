"""Tables written into the folder that driver and executors share, where lineage ends."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one only where none is set (tests)."""
    if folder := spark.conf.get("spark.checkpoint.dir", None):
        return folder
    held = spark.sparkContext._jsc.sc().getCheckpointDir()
    if held.isDefined():
        return held.get()
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    folder = "file://" + tempfile.mkdtemp(prefix="shared-")
    spark.sparkContext.setCheckpointDir(folder)
    return folder


def _written(spark: SparkSession) -> list[str]:
    context = spark.sparkContext
    if not hasattr(context, "_shiftscan_written"):
        context._shiftscan_written = []
    return context._shiftscan_written


def new_path(spark: SparkSession, name: str) -> str:
    """A path of its own in the shared folder, on the list of what may be deleted."""
    path = f"{shared_folder(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    _written(spark).append(path)
    return path


def stored(df: DataFrame, name: str = "step") -> DataFrame:
    """Write a table into the shared folder and read it again: lineage ends there."""
    path = new_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def mark(spark: SparkSession) -> int:
    """Where the list of written tables ends now."""
    return len(_written(spark))


def clear(spark: SparkSession, since: int = 0, keep_last: bool = False) -> int:
    """Deletes what this session has written since a mark, once no result needs it any more; ``keep_last``: but the newest."""
    paths = _written(spark)
    gone = paths[since : len(paths) - keep_last]
    for path in gone:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
    paths[since : len(paths) - keep_last] = []
    return len(gone)
