"""Intermediate tables in the folder that the cluster shares, so that they are made once and survive lost executors."""

from __future__ import annotations

import gc
import os
import re
import time
from collections.abc import Hashable
from concurrent.futures import ThreadPoolExecutor

from py4j.protocol import Py4JJavaError
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder that the driver and all executors see: spark.checkpoint.dir. One of our own only where driver and executors are one process."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base
    if re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        return "/tmp/checkpoints"
    raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")


def checkpointed(df: DataFrame) -> DataFrame:
    """Cuts the lineage through the shared folder."""
    sc = df.sparkSession.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint(eager=True)


def written(df: DataFrame) -> DataFrame:
    """The same rows read from a table in the shared folder: lineage is cut, columns are compressed."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/tables/{spark.sparkContext.applicationId}-{os.urandom(8).hex()}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.__dict__["table_path"] = path
    return out


def dropped(*tables: DataFrame) -> None:
    """Deletes tables that ``written`` made and that nothing reads any more."""
    for t in tables:
        sc = t.sparkSession.sparkContext
        path = sc._jvm.org.apache.hadoop.fs.Path(t.__dict__["table_path"])
        path.getFileSystem(sc._jsc.hadoopConfiguration()).delete(path, True)


def freed(spark: SparkSession) -> None:
    """Lets Spark delete the shuffle files of finished steps now: its cleaner acts only after the driver has collected its garbage.

    The last job's plan is still held, so one of a row comes first; what that collection frees holds more, so there are two.
    """
    spark.range(1).write.format("noop").mode("overwrite").save()
    for _ in range(2):
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.3)
    trimmed(spark)


def trimmed(spark: SparkSession) -> bool:
    """Returns the driver's free native memory (its compiler's and its buffers', outside the heap) to the system; False where the Java in use has no command for it."""
    gateway, jvm = spark.sparkContext._gateway, spark.sparkContext._jvm
    server, commands = jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand")
    kinds = gateway.new_array(jvm.java.lang.Class, 4)
    for k, name in enumerate(("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")):
        kinds[k] = jvm.java.lang.Class.forName(name)
    given = gateway.new_array(jvm.java.lang.Object, 4)
    given[0], given[1] = commands, "systemTrimNativeHeap"
    try:  # by the interface, as the server's own class is not open to callers
        jvm.java.lang.Class.forName("javax.management.MBeanServer").getMethod("invoke", kinds).invoke(server, given)
    except Py4JJavaError:
        return False
    return True


def written_all(tables: dict[Hashable, DataFrame]) -> dict[Hashable, DataFrame]:
    """Several tables that do not depend on each other, written side by side."""
    if len(tables) < 2:
        return {k: written(t) for k, t in tables.items()}
    session = next(iter(tables.values())).sparkSession
    with ThreadPoolExecutor(min(8, len(tables))) as pool:
        jobs = {k: pool.submit(inheritable_thread_target(session)(written), t) for k, t in tables.items()}
        return {k: job.result() for k, job in jobs.items()}
