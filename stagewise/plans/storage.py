"""Where built tables are kept: the shared folder of ``spark.checkpoint.dir``, or a folder that the caller names."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a temporary one only where none is set and all runs in one process."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder and not sc.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir names no folder that driver and executors share")
        sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="stagewise-"))
    return sc._jsc.sc().getCheckpointDir().get()


_WRITTEN: list[str] = []


def forget(spark: SparkSession) -> int:
    """Delete every folder that ``keep`` named by itself in this session; the number of folders. Frames read from them are void after it."""
    done = 0
    while _WRITTEN:
        path = spark._jvm.org.apache.hadoop.fs.Path(_WRITTEN.pop())
        done += bool(path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True))
    return done


def keep(df: DataFrame, path: str | None = None) -> DataFrame:
    """Write a frame as Parquet and read it back: lineage ends there."""
    if path is None:
        path = f"{shared_folder(df.sparkSession)}/{uuid.uuid4().hex}"
        _WRITTEN.append(path)
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
