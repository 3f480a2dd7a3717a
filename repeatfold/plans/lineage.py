"""Cutting lineage in a folder that all executors share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_OWN: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``, or the context's checkpoint folder.

    An own temporary folder stands in only where neither is set and the master is local, as in tests; executors of a cluster would not see it,
    so there its lack is an error.
    """
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if named:
        return named.rstrip("/")
    if not sc.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _OWN:
        _OWN.append(tempfile.mkdtemp(prefix="spark-shared-"))
        atexit.register(shutil.rmtree, _OWN[0], ignore_errors=True)
    return _OWN[0]


def _path(spark: SparkSession, name: str):
    """The Hadoop path of ``name`` and its file system."""
    path = spark._jvm.org.apache.hadoop.fs.Path(name)
    return path, path.getFileSystem(spark._jsc.hadoopConfiguration())


def cut(df: DataFrame) -> DataFrame:
    """``df`` written to the shared folder and read again; the files go with the application, or sooner by ``drop_cut``."""
    spark = df.sparkSession
    name = f"{shared_dir(spark)}/cut-{uuid.uuid4().hex}"
    path, files = _path(spark, name)
    files.deleteOnExit(path)
    df.write.parquet(name)
    out = spark.read.schema(df.schema).parquet(name)
    out._cut_at = name
    return out


def drop_cut(df: DataFrame) -> None:
    """Removes the files behind a frame of ``cut`` that nothing reads any more."""
    path, files = _path(df.sparkSession, df._cut_at)
    files.delete(path, True)
