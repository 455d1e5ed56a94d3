"""Intermediate tables in the folder that driver and executors share."""

from __future__ import annotations

import atexit
import gc
import shutil
import tempfile
import time
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder named in spark.checkpoint.dir; where that is unset (local tests) a temporary one, which a cluster couldn't share."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = getattr(shared_dir, "_own", None)
        if base is None:
            folder = tempfile.mkdtemp(prefix="deltahop-")
            atexit.register(shutil.rmtree, folder, True)
            base = shared_dir._own = f"file://{folder}"
    return base.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex[:12]}"


def stored(df: DataFrame, name: str, free: bool = False) -> tuple[DataFrame, str]:
    """Write a table to the shared folder and read it back: cuts lineage and survives lost executors.

    free: let Spark delete the shuffle files behind it before going on.
    """
    spark, schema = df.sparkSession, df.schema
    path = fresh_path(spark, name)
    df.write.parquet(path)
    del df  # else the plan, and with it its shuffle files, would outlive the call below
    if free:
        release(spark)
    return spark.read.schema(schema).parquet(path), path


def release(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of finished steps now. Plans are collected in one pass of the driver's collector and their
    shuffles are let go in the next one."""
    for _ in range(2):
        gc.collect()
        spark._jvm.System.gc()
        time.sleep(0.3)


def drop_path(spark: SparkSession, path: str) -> None:
    """Delete an intermediate table that no later step reads."""
    jvm = spark._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)
