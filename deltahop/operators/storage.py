"""Results of iterations are written to the folder in spark.checkpoint.dir, which cuts lineage and survives lost executors."""

from __future__ import annotations

import atexit
import gc
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_path(spark: SparkSession, name: str) -> str:
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = getattr(shared_path, "own", None)
        if base is None:
            folder = tempfile.mkdtemp(prefix="deltahop-")
            atexit.register(shutil.rmtree, folder, True)
            base = shared_path.own = f"file://{folder}"
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex[:12]}"


def drop(spark: SparkSession, path: str) -> None:
    """Delete an intermediate table that no later step reads."""
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


def stored(df: DataFrame, name: str = "step", free: bool = False) -> DataFrame:
    """Writes a table and reads it back. free: lets Spark delete the shuffle files behind it at once, not when the driver's memory is short."""
    spark, schema = df.sparkSession, df.schema
    path = shared_path(spark, name)
    df.write.parquet(path)
    if free:
        for _ in range(2):  # plans go in one pass of the collector, their shuffles in the next
            gc.collect()
            spark._jvm.System.gc()
    return spark.read.schema(schema).parquet(path)
