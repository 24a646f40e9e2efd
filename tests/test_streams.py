"""Streams give what the batch gives."""

import shutil

import pytest
from pyspark.sql import functions as F

from layermul.matrix import SparseMatrix
from layermul.plans.multiply import catalyst
from layermul.streaming import stream
from layermul.workloads import queries

EVENTS = "/root/testdata/sf0.001/events.parquet"


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """The events in four files, in no order of time."""
    out = tmp_path_factory.mktemp("events")
    spark.read.parquet(EVENTS).repartition(4, "event_id").write.mode("overwrite").parquet(f"{out}/all")
    for k, f in enumerate(sorted((out / "all").glob("part*.parquet"))):
        shutil.copy(f, out / f"events{k}.parquet")
    shutil.rmtree(out / "all")
    return str(out)


def test_tumbling_counts_all_in_complete_mode(spark, folder):
    stream.run_to_end(stream.windowed_matrix(stream.event_stream(spark, folder)), "complete", name="all_windows")
    want = spark.read.parquet(EVENTS).groupBy(F.date_trunc("hour", F.col("ts").cast("timestamp")).cast("timestamp_ntz").alias("start"), F.col("user_id").alias("i"), "event_type").agg(F.count(F.lit(1)).alias("v"))
    assert spark.table("all_windows").exceptAll(want).isEmpty() and spark.table("all_windows").count() == want.count()


def test_append_never_invents_rows(spark, folder):
    stream.run_to_end(stream.windowed_matrix(stream.event_stream(spark, folder, 4)), "append", name="closed_windows")
    assert 0 < spark.table("closed_windows").count() <= spark.read.parquet(EVENTS).count()


def test_delta_product_equals_the_batch(spark, folder):
    b = SparseMatrix.rows_of(spark, [(x, y, 1 + x * y) for x in range(4) for y in range(3)], 4, 3)
    rows = stream.event_stream(spark, folder).select(F.col("user_id").alias("i"), F.pmod("event_id", F.lit(4)).alias("j"))
    delta = stream.DeltaProduct(b, 10**6)
    stream.run_to_end(rows, each=lambda batch, n: delta.add(batch.groupBy("i", "j").agg(F.count(F.lit(1)).alias("v")), n))
    a = spark.read.parquet(EVENTS).groupBy(F.col("user_id").alias("i"), F.pmod("event_id", F.lit(4)).alias("j")).agg(F.count(F.lit(1)).alias("v"))
    want = catalyst(SparseMatrix(a, 10**6, 4), b).df
    assert delta.last == 3 and delta.product.df.exceptAll(want).isEmpty() and delta.product.df.count() == want.count()
    delta.add(spark.createDataFrame([(1, 1, 1)], "i bigint, j bigint, v bigint"), 3)  # a replayed batch
    assert delta.product.df.exceptAll(want).isEmpty()


def test_pairs_of_events(spark, folder):
    e = stream.event_stream(spark, folder, 4)
    stream.run_to_end(stream.click_purchases(e.where("event_type = 'click'"), stream.event_stream(spark, folder, 4).where("event_type = 'purchase'")), name="pairs")
    t = spark.read.parquet(EVENTS).withColumn("ts", F.col("ts").cast("timestamp"))
    c, p = t.where("event_type = 'click'"), t.where("event_type = 'purchase'")
    want = c.alias("c").join(p.alias("p"), F.expr("c.user_id = p.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 10 MINUTES")).count()
    assert spark.table("pairs").count() == want


@pytest.mark.parametrize("mode", ["complete", "append"])
def test_stored_results_are_those_of_the_batch(spark, folder, mode):
    at = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(at)
    events = stream.event_stream(spark, folder)
    got = stream.stored(stream.windowed_matrix(events) if mode == "complete" else stream.once_per_event(events, "400 days").select("event_id"), mode)
    t = spark.read.parquet(EVENTS)
    by_hour = t.groupBy(F.date_trunc("hour", F.col("ts").cast("timestamp")).cast("timestamp_ntz").alias("start"), F.col("user_id").alias("i"), "event_type").agg(F.count(F.lit(1)).alias("v"))
    want = by_hour if mode == "complete" else t.select("event_id").distinct()
    assert got.exceptAll(want).isEmpty() and got.count() == want.count() > 0
    assert spark.conf.get(at) == before


@pytest.mark.parametrize("name", ["dedupe", "session", "tumbling", "sliding"])
def test_queries_leave_results_in_files(spark, name):
    """Not in a table of the driver's memory."""
    assert queries()[f"stream_{name}"](spark, "/root/testdata/sf0.001").inputFiles()
