"""Matrices over streams: a matrix per window, products of a growing matrix, edges from event pairs."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery

from layermul.matrix import SparseMatrix
from layermul.plans.multiply import catalyst
from layermul.semiring import PLUS_TIMES, Semiring
from layermul.session import fresh_path, materialize

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, files_at_once: int = 1, pattern: str = "events*.parquet") -> DataFrame:
    """Events replayed from a folder of Parquet files; ts becomes a timestamp, which watermarks need."""
    read = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_at_once).option("pathGlobFilter", pattern)
    return read.parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def run_to_end(df: DataFrame, mode: str = "append", each=None, name: str | None = None) -> StreamingQuery:
    """All that is there, in micro-batches, to a memory table or to each(batch, number)."""
    writer = df.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", fresh_path(df.sparkSession, "stream"))
    writer = writer.foreachBatch(each) if each else writer.format("memory").queryName(name)
    query = writer.start()
    query.awaitTermination()
    return query


def stored(df: DataFrame, mode: str = "append") -> DataFrame:
    """All that is there, in micro-batches, as a table in the shared folder; nothing of it is held by the driver.
    In complete mode every batch writes the whole result anew, and the last one stands."""
    spark, path = df.sparkSession, fresh_path(df.sparkSession, "told")
    numbers: list[int] = []

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{number}")
        if number not in numbers:
            numbers.append(number)

    with rocksdb(spark):
        run_to_end(df, mode, each=write)
    if not numbers:
        return spark.createDataFrame([], df.schema)
    return spark.read.schema(df.schema).parquet(*[f"{path}/{n}" for n in (numbers[-1:] if mode == "complete" else numbers)])


@contextmanager
def rocksdb(spark: SparkSession) -> Iterator[None]:
    """Queries started in here hold their state in RocksDB on the executors' disks, within one bound of memory
    an executor, not on their heaps."""
    wanted = {"providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider", "rocksdb.boundedMemoryUsage": "true", "rocksdb.maxMemoryUsageMB": "400"}
    wanted = {f"spark.sql.streaming.stateStore.{k}": v for k, v in wanted.items()}
    before = {k: spark.conf.get(k, None) for k in wanted}
    try:
        for k, v in wanted.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def windowed_matrix(events: DataFrame, kind: str = "tumbling", delay: str = "10 minutes") -> DataFrame:
    """(start, i, event_type, v): one user x type matrix for every tumbling hour, every hour that
    starts each quarter (sliding), or every session of a user with gaps under half an hour."""
    late = events.withWatermark("ts", delay)
    span = {"tumbling": F.window("ts", "1 hour"), "sliding": F.window("ts", "1 hour", "15 minutes"), "session": F.session_window("ts", "30 minutes")}[kind]
    grouped = late.groupBy(span.alias("w"), F.col("user_id").alias("i"), "event_type") if kind != "session" else late.groupBy(span.alias("w"), F.col("user_id").alias("i"))
    counted = grouped.agg(F.count(F.lit(1)).alias("v"))
    return counted.select(F.col("w.start").cast("timestamp_ntz").alias("start"), *[c for c in counted.columns if c != "w"])


def once_per_event(events: DataFrame, delay: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


class DeltaProduct:
    """C = A B kept up to date while entries of A arrive: each batch adds its own product, a merge in
    time like the one across layers. Batches that are replayed after a failure are not added twice."""

    def __init__(self, b: SparseMatrix, nrows: int, semiring: Semiring = PLUS_TIMES):
        self.b, self.nrows, self.semiring = b, nrows, semiring
        self.c: DataFrame | None = None
        self.last = -1

    def add(self, batch: DataFrame, number: int) -> None:
        if number <= self.last:
            return
        delta = catalyst(SparseMatrix(batch.select("i", "j", "v"), self.nrows, self.b.nrows), self.b, self.semiring).df
        both = delta if self.c is None else self.c.unionByName(delta)
        self.c = materialize(both.groupBy("i", "j").agg(self.semiring.merge(F.col("v")).alias("v")), "delta")
        self.last = number

    @property
    def product(self) -> SparseMatrix:
        return SparseMatrix(self.c, self.nrows, self.b.ncols)


class _ColumnState(StatefulProcessor):
    """Keeps each column's entries and tells its size and sum after every batch."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.entries = handle.getMapState("entries", "i bigint", "v bigint")

    def handleInputRows(self, key: Any, rows: Iterator[pd.DataFrame], timerValues: Any) -> Iterator[pd.DataFrame]:
        for frame in rows:
            for i, v in frame.groupby("i").v.sum().items():
                held = self.entries.getValue((int(i),))
                self.entries.updateValue((int(i),), (int(v) + (held[0] if held else 0),))
        values = [v[0] for _, v in self.entries.iterator()]
        yield pd.DataFrame({"j": [key[0]], "n": [len(values)], "total": [sum(values)]})

    def close(self) -> None:
        pass


def column_store(entries: DataFrame) -> DataFrame:
    """(j, n, total) of each column that a batch touched, from state that holds the columns; entries
    (i, j, v) may repeat. Needs the RocksDB state store."""
    return entries.groupBy("j").transformWithStateInPandas(_ColumnState(), "j bigint, n bigint, total bigint", "Update", "None")


def click_purchases(clicks: DataFrame, purchases: DataFrame, minutes: int = 10, delay: str = "10 minutes") -> DataFrame:
    """(i, click, purchase): stream-stream join of a user's purchases with clicks in the minutes before."""
    c = clicks.withWatermark("ts", delay).select(F.col("user_id").alias("i"), F.col("event_id").alias("click"), F.col("ts").alias("cts"))
    p = purchases.withWatermark("ts", delay).select(F.col("user_id").alias("pi"), F.col("event_id").alias("purchase"), F.col("ts").alias("pts"))
    near = (F.col("i") == F.col("pi")) & (F.col("pts") >= F.col("cts")) & (F.col("pts") <= F.col("cts") + F.expr(f"INTERVAL {minutes} MINUTES"))
    return c.join(p, near).select("i", "click", "purchase")
