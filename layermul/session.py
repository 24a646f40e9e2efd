"""Session settings at run time, and tables in the shared folder that cut lineage."""

from __future__ import annotations

import os
import re
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession


def reach_workers(spark: SparkSession) -> None:
    """Python workers that share this machine's folders find the package where the driver found it;
    on a cluster it is installed or shipped as usual."""
    root = str(Path(__file__).resolve().parent.parent)
    env = spark.sparkContext.environment
    if root not in env.get("PYTHONPATH", "").split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(filter(None, [env.get("PYTHONPATH", ""), root]))


def configure(spark: SparkSession) -> SparkSession:
    """Let a join and an aggregate reuse a partitioning on some of their keys: the grid plans are
    dealt out by cell once and joined and combined inside the cells."""
    reach_workers(spark)
    spark.conf.set("spark.sql.requireAllClusterKeysForCoPartition", "false")
    return spark


def shared_root(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir. Only a local session, whose workers share this machine, gets a
    temporary one where that is unset; on a cluster it must be set."""
    root = spark.conf.get("spark.checkpoint.dir", None) or getattr(spark, "_layermul_scratch", None)
    if not root:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        root = spark._layermul_scratch = tempfile.mkdtemp(prefix="layermul-")
    return root.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_root(spark)}/layermul/{name}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str, compression: str | None = None, rows_a_file: int = 0) -> DataFrame:
    """Write df once and read it back: later plans start from files that survive lost executors."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    df.write.option("maxRecordsPerFile", rows_a_file).parquet(path, compression=compression)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


def discard(*frames: DataFrame) -> None:
    """Delete the tables that materialize() wrote for these frames, once nothing reads them any more."""
    for df in frames:
        spark, path = df.sparkSession, df._scratch_path
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)
