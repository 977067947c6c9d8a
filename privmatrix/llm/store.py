"""Lineage cuts in the folder that all executors share, and the memory of the driver between them."""

from __future__ import annotations

from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, SparkSession

from privmatrix.llm import textscan
from privmatrix.sources.store import shared_folder, written

__all__ = ["dropped", "eased", "shared_folder", "written"]


def dropped(df: DataFrame) -> None:
    """Remove the files that ``written`` made for ``df``, which must not be used again."""
    spark = df.sparkSession
    for file in df.inputFiles():
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(file)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, False)


def eased(spark: SparkSession) -> None:
    """Give the driver's unused memory back to the system.

    Planning and compiling leave garbage in the heap and freed pieces in the many arenas of the C library, which keep their pages
    (after some hundred plans as much as the live heap). JVMs or C libraries without that command keep the latter.
    """
    jvm = spark.sparkContext._jvm
    jvm.System.gc()
    try:
        server = jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer()  # of a class that only its interface gives access to
        call = next(m for m in jvm.java.lang.Class.forName("javax.management.MBeanServer").getMethods() if m.getName() == "invoke")
        arguments = spark.sparkContext._gateway.new_array(jvm.java.lang.Object, 4)
        arguments[0], arguments[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        call.invoke(server, arguments)
    except Py4JError:
        pass
    textscan.trim()
