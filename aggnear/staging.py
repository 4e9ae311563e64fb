"""Tables staged in the folder that driver and executors share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; only a local master may go without and gets a temporary one."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if root:
        return root
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    root = tempfile.mkdtemp(prefix="aggnear-")
    atexit.register(shutil.rmtree, root, ignore_errors=True)
    spark.sparkContext.setCheckpointDir(root)
    return spark.sparkContext.getCheckpointDir()


#: Folders that this process has named, for ``drop_staged``.
_made: list[str] = []


def new_folder(spark: SparkSession, name: str) -> str:
    _made.append(f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}")
    return _made[-1]


def drop_staged(spark: SparkSession) -> int:
    """Remove every table that this process has staged, once no answer is read from them any more; returns how many."""
    many = 0
    while _made:
        at = spark._jvm.org.apache.hadoop.fs.Path(_made.pop())
        many += bool(at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True))
    return many


def stage(df: DataFrame, name: str, path: str | None = None) -> DataFrame:
    """Write df and read it again: lineage ends, and recovery is a re-read."""
    spark = df.sparkSession
    path = path or new_folder(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
