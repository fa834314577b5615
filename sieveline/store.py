"""Materialisation in the folder that all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Folders written so far, for :func:`sweep`.
_made: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; an own one where it is unset and the master is local."""
    sc = spark.sparkContext
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        if not folder and not (sc.master == "local" or sc.master.startswith("local[")):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors reach")
        sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="shared-"))
    return folder or sc._jsc.sc().getCheckpointDir().get()


def scratch(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder."""
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    _made.append(path)
    return path


def sweep(spark: SparkSession) -> int:
    """Delete what :func:`scratch` and :func:`stored` have written; frames read from there end with it."""
    conf, n = spark._jsc.hadoopConfiguration(), len(_made)
    while _made:
        path = spark._jvm.org.apache.hadoop.fs.Path(_made.pop())
        path.getFileSystem(conf).delete(path, True)
    return n


def cut(df: DataFrame) -> DataFrame:
    """Materialise a frame, so that lost executors cost no recomputation."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write a frame as a table of the shared folder and read it, so that its size is known to the planner."""
    path = scratch(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def small(df: DataFrame, rows: int = 10_000) -> DataFrame:
    """A frame to broadcast, checked to have few rows; an error where it has more."""
    if df.limit(rows + 1).count() > rows:
        raise ValueError(f"more than {rows} rows are not broadcast")
    return F.broadcast(df)
