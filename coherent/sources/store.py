"""Results that several plans read, kept in the folder that all executors share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or a temporary folder where none is set (tests, one machine), removed at the end."""
    sc = spark.sparkContext
    told = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not told:
        told = "file://" + tempfile.mkdtemp(prefix="coherent-")
        atexit.register(shutil.rmtree, told.removeprefix("file://"), True)
        sc.setCheckpointDir(told)
    return told.rstrip("/")


def fresh_path(spark: SparkSession, tag: str) -> str:
    """A new path in the shared folder, deleted when the application ends."""
    path = f"{shared_dir(spark)}/coherent/{tag}-{uuid.uuid4().hex}"
    there = spark._jvm.org.apache.hadoop.fs.Path(path)
    there.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).deleteOnExit(there)
    return path


def keep(df: DataFrame, tag: str = "kept") -> DataFrame:
    """Write `df` and read it again: each row is computed once, the plan starts anew, and lost executors cost nothing."""
    path = fresh_path(df.sparkSession, tag)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
