"""Lineage cuts in the folder that the cluster shares."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from functools import lru_cache

from pyspark.sql import DataFrame, SparkSession


@lru_cache(maxsize=1)
def _own() -> str:
    """A folder of this process, in local mode only; it goes when the process ends."""
    path = tempfile.mkdtemp(prefix="cyclefold-")
    atexit.register(shutil.rmtree, path, ignore_errors=True)
    return path


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; where it is unset, one of this process, in local mode only."""
    context = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if named:
        return named
    if not context.master.startswith("local") or context.master.startswith("local-cluster"):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    return _own()


def new_folder(spark: SparkSession) -> str:
    """The path of a folder of its own in the shared folder. It goes when the session's process ends."""
    path = f"{shared_dir(spark).rstrip('/')}/cyclefold/{uuid.uuid4().hex}"
    atexit.register(remove, spark, path)
    return path


def _file_system(spark: SparkSession, path: str):
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()), at


def exists(spark: SparkSession, *parts: str) -> bool:
    system, at = _file_system(spark, "/".join(parts))
    return bool(system.exists(at))


def remove(spark: SparkSession, path: str) -> None:
    """Deletes a folder and what is in it. A session that has ended leaves it to the folder's own cleaning."""
    if spark.sparkContext._jsc is not None:
        system, at = _file_system(spark, path)
        system.delete(at, True)


def materialise(df: DataFrame) -> DataFrame:
    """Write ``df`` once as Parquet in the shared folder and read it back.

    Unlike ``checkpoint()`` this runs the plan a single time, and the files outlive any executor.
    """
    spark = df.sparkSession
    path = new_folder(spark)
    df.write.parquet(path)
    written = spark.read.schema(df.schema).parquet(path)
    written._written_to = path
    return written


def forget(written: DataFrame) -> None:
    """Deletes what ``materialise`` wrote, once nothing will read it again."""
    remove(written.sparkSession, written._written_to)
