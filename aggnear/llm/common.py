"""Shared plumbing of the corpus operators: the shared work folder, staged tables and block joins."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..staging import new_folder

#: Words are runs of anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"


def stage(df: DataFrame, name: str, path: str | None = None, codec: str | None = None) -> DataFrame:
    """Write df as a table in the shared folder and read it again: lineage ends, recovery is a re-read.

    zstd is for few large tables only: its native buffers stay with an executor that writes many files.
    """
    spark = df.sparkSession
    path = path or new_folder(spark, name)
    w = df.write
    (w.option("compression", codec) if codec else w).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._staged_at = path
    return out


def drop(*staged: DataFrame | str) -> None:
    """Remove staged tables that no later plan reads."""
    for x in staged:
        spark = SparkSession.active()
        path = x if isinstance(x, str) else x._staged_at
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def positional(docs: DataFrame) -> tuple[DataFrame, dict[str, str]]:
    """docs with its columns named by position, which no helper column can clash with, and the names by column."""
    names = {c: f"c{i}" for i, c in enumerate(docs.columns)}
    return docs.toDF(*names.values()), names


def slices(batches, rows: int = 128):
    """Record batches cut into slices of few rows, so that long texts are unpacked a few at a time."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)
        pa.default_memory_pool().release_unused()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def word_count(text: Column) -> Column:
    """Number of words of a text, 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def parallelism(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
