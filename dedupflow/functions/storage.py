"""Durable intermediate tables in the folder that all executors share."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid
from functools import lru_cache

from pyspark.sql import DataFrame, SparkSession


@lru_cache(maxsize=1)
def _own_dir() -> str:
    made = tempfile.mkdtemp(prefix="dedupflow-")
    atexit.register(shutil.rmtree, made, ignore_errors=True)
    return f"file://{made}"


def shared_dir(spark: SparkSession) -> str:
    """Folder all executors share: ``spark.checkpoint.dir``; a temporary one of this process only where all executors are threads of it."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not where and not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return (where or _own_dir()).rstrip("/")


def scratch(spark: SparkSession, what: str) -> str:
    """A fresh path in the shared folder, removed when the driver's JVM ends."""
    path = f"{shared_dir(spark)}/dedupflow-{what}-{uuid.uuid4().hex}"
    jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
    fs = jpath.getFileSystem(spark._jsc.hadoopConfiguration())
    fs.mkdirs(jpath)
    fs.deleteOnExit(jpath)
    return path


def written(df: DataFrame, what: str) -> DataFrame:
    """Cuts lineage: the rows as a Parquet table in the shared folder, so a lost executor costs a re-read, not a re-run."""
    path = scratch(df.sparkSession, what)
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Removes a table made by ``written`` once nothing reads it any more."""
    spark = df.sparkSession
    for f in df.inputFiles()[:1]:
        jpath = spark._jvm.org.apache.hadoop.fs.Path(f).getParent()
        jpath.getFileSystem(spark._jsc.hadoopConfiguration()).delete(jpath, True)


def reclaim(spark: SparkSession) -> None:
    """Has Spark remove the shuffle files of frames that nothing refers to any more, which else waits for the driver's next collection."""
    spark.sparkContext._jvm.System.gc()
