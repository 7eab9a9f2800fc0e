"""Lineage cuts that survive a lost executor."""

from __future__ import annotations

import atexit
import contextlib
import gc
import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder for reliable checkpoints: spark.checkpoint.dir of the session; a temporary one only in local mode."""
    set_by_cluster = spark.conf.get("spark.checkpoint.dir", None)
    if set_by_cluster:
        return set_by_cluster
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return os.path.join(tempfile.gettempdir(), "densereps-checkpoints")


def cut(df: DataFrame) -> DataFrame:
    """Compute df once and continue from reliable files in the shared folder; they go at the end of the session."""
    spark = df.sparkSession
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(shared_dir(spark))
        remove_at_end(spark, context.getCheckpointDir())
    return df.checkpoint()


def remove(spark: SparkSession, path: str) -> None:
    with contextlib.suppress(Exception):  # the context may be gone
        hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
        hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hadoop, True)


def remove_at_end(spark: SparkSession, path: str) -> None:
    atexit.register(remove, spark, path)


def forget_unused(spark: SparkSession) -> None:
    """Have shuffle files dropped that no table refers to any more: Spark's cleaner learns of them when the driver collects garbage.

    What the driver's JVM has freed outside its heap goes back to the system too, where the platform can do that.
    """
    gc.collect()
    spark._jvm.System.gc()
    with contextlib.suppress(Exception):  # other JVMs don't have it
        jvm, new = spark._jvm, spark.sparkContext._gateway.new_array
        call = next(m for m in jvm.java.lang.Class.forName("javax.management.MBeanServerConnection").getMethods() if m.getName() == "invoke")
        args = new(jvm.java.lang.Object, 4)
        args[0], args[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        call.invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), args)


def stored(df: DataFrame) -> DataFrame:
    """Like cut(), as a compressed columnar table in the shared folder, for wide or many rows; kept to the end."""
    spark = df.sparkSession
    path = os.path.join(shared_dir(spark), "densereps-tables", f"{spark.sparkContext.applicationId}-{uuid.uuid4().hex}")
    df.write.parquet(path)
    remove_at_end(spark, path)
    return spark.read.parquet(path)
