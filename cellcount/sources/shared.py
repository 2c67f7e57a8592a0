"""Intermediate tables in the folder that the driver and all executors share; they survive lost executors."""

from __future__ import annotations

import gc
import tempfile
import uuid

from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, SparkSession

from ..cluster import ship


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session; a folder of this machine, set once, where none is set (local tests)."""
    own = spark.conf.get("spark.checkpoint.dir", None)
    if own:
        return own.rstrip("/")
    held = spark.sparkContext._jsc.sc().getCheckpointDir()
    if not held.isDefined():
        spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="cellcount-"))
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
    return str(held.get()).rstrip("/")


def fresh(spark: SparkSession, name: str) -> str:
    """A path in the shared folder that nothing uses yet."""
    ship(spark)
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def store(df: DataFrame, name: str, by: tuple[str, ...] = ()) -> DataFrame:
    """Write ``df`` into the shared folder, partitioned ``by`` columns, and read it back."""
    spark, path = df.sparkSession, fresh(df.sparkSession, name)
    df.write.partitionBy(*by).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(spark: SparkSession, path: str) -> None:
    """Delete a path of the shared folder."""
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def release(spark: SparkSession) -> None:
    """Let the driver find out which shuffle files and broadcasts nothing uses any more; Spark then deletes them.

    Spark's cleaner acts on what the driver's garbage collection finds, which a large heap may not need for a long time.
    What the driver's compilers and planners freed outside the heap goes back to the system as well, where the JVM can do so.
    """
    gc.collect()  # Python's handles keep the JVM's objects
    spark.sparkContext._jvm.System.gc()
    trim(spark)


def trim(spark: SparkSession) -> bool:
    """Return freed memory outside the driver's heap to the system; False where the JVM does not have this command."""
    sc = spark.sparkContext
    lang, args = sc._jvm.java.lang, sc._gateway.new_array(sc._jvm.java.lang.Object, 4)
    try:
        args[0], args[1] = sc._jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        # The server's own class is not open to reflection, its interface is.
        call = next(m for m in lang.Class.forName("javax.management.MBeanServer").getMethods() if m.getName() == "invoke")
        call.invoke(lang.management.ManagementFactory.getPlatformMBeanServer(), args)
    except Py4JError:
        return False
    return True


def size_of(spark: SparkSession, path: str) -> int:
    """Bytes under a path of the shared folder."""
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(p).getLength()
