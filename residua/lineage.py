"""Lineage cuts that survive lost executors: tables written to the shared checkpoint folder."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: The temporary folder of a local session that names no shared one.
LOCAL: list[str] = []


def folder(spark: SparkSession) -> str:
    """A new path in the folder ``spark.checkpoint.dir`` names. A local session without one (tests) gets a temporary folder, a cluster an error."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        if not LOCAL:
            LOCAL.append(tempfile.mkdtemp(prefix="flow-"))
            atexit.register(shutil.rmtree, LOCAL[0], ignore_errors=True)
        base = LOCAL[0]
    return f"{base.rstrip('/')}/flow-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    path = folder(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def drop(spark: SparkSession, paths: list[str]) -> None:
    """Deletes written tables that nothing reads any more."""
    for path in paths:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
