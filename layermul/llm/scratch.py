"""Shared-folder tables: lineage is cut by written Parquet, never by executor-local copies."""

from __future__ import annotations

import gc

import pyarrow as pa
from py4j.protocol import Py4JError
from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from layermul.session import discard, fresh_path, reach_workers

__all__ = ["bound_arrow", "broadcast_if_small", "counted", "discard", "fresh_path", "materialize", "observed", "release", "table"]

#: Rows of a narrow side that may be broadcast; larger sides are joined by shuffle.
BROADCAST_ROWS = 1_000_000
#: Bytes of rows that Spark hands to a Python worker at once.
ARROW_BYTES = 8 << 20
#: Share of the driver's heap in use from which finished phases are let go.
HEAP_SHARE = 0.3


def bound_arrow(spark: SparkSession) -> None:
    """Batches for Python are bounded by bytes, however long the texts are (a run-time setting)."""
    reach_workers(spark)
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", ARROW_BYTES)


def release(spark: SparkSession) -> None:
    """Let go of finished phases: Spark deletes the shuffle files and broadcasts of plans that nothing
    refers to when the driver collects its garbage, which it may otherwise do much later."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    spark.sparkContext._jvm.System.gc()
    _trim_native(spark)


def _trim_native(spark: SparkSession) -> None:
    """Have the driver's JVM return native memory that it has freed to the system: its allocator keeps
    hundreds of MB in the arenas of compiler and scheduler threads otherwise. A JVM without this
    command (before JDK 17.0.9, or not on Linux) is left as it is."""
    jvm, array = spark.sparkContext._jvm, spark.sparkContext._gateway.new_array
    kind = jvm.java.lang.Class.forName
    try:
        if not hasattr(spark.sparkContext, "_layermul_trim"):
            kinds = array(jvm.java.lang.Class, 4)
            for n, name in enumerate(("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")):
                kinds[n] = kind(name)
            args = array(jvm.java.lang.Object, 4)
            args[0], args[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
            args[2], args[3] = array(jvm.java.lang.Object, 0), array(jvm.java.lang.String, 0)
            spark.sparkContext._layermul_trim = kind("javax.management.MBeanServer").getMethod("invoke", kinds), jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), args
        if spark.sparkContext._layermul_trim:
            method, server, args = spark.sparkContext._layermul_trim
            method.invoke(server, args)
    except Py4JError:
        spark.sparkContext._layermul_trim = None


def _release_if_full(spark: SparkSession) -> None:
    _trim_native(spark)
    heap = spark.sparkContext._jvm.Runtime.getRuntime()
    if heap.totalMemory() - heap.freeMemory() > HEAP_SHARE * heap.maxMemory():
        release(spark)


def observed(df: DataFrame, name: str, **measures: Column) -> tuple[DataFrame, dict]:
    """df written once to the shared folder, as a reader of it, and aggregates of its rows, taken
    while they were written. Later plans start from files that survive lost executors. Void columns
    are not allowed in Parquet and must be cast before."""
    spark, path = df.sparkSession, fresh_path(df.sparkSession, name)
    seen = Observation() if measures else None
    told = df.observe(seen, *[c.alias(k) for k, c in measures.items()]) if measures else df
    told.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    _release_if_full(spark)
    return out, dict.fromkeys(measures) | seen.get if measures else {}


def materialize(df: DataFrame, name: str) -> DataFrame:
    return observed(df, name)[0]


def counted(df: DataFrame, name: str) -> tuple[DataFrame, int]:
    out, told = observed(df, name, n=F.count(F.lit(1)))
    return out, told["n"] or 0


def broadcast_if_small(df: DataFrame, rows: int, bound: int = BROADCAST_ROWS) -> DataFrame:
    """A broadcast hint behind a check of the counted rows; beyond the bound Spark shuffles."""
    return F.broadcast(df) if rows <= bound else df


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
