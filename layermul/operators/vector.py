"""Sparse vectors as tables (i, v), and their products with matrices."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from layermul.matrix import SparseMatrix
from layermul.semiring import Semiring


def apply(v: DataFrame, f: Callable[[Column], Column]) -> DataFrame:
    return v.select("i", f(F.col("v")).alias("v"))


def mxv(a: SparseMatrix, v: DataFrame, semiring: Semiring) -> DataFrame:
    """(i, v): rows of a that meet the vector."""
    points = a.df.toDF("i", "k", "a").join(v.toDF("k", "x"), "k")
    return points.groupBy("i").agg(semiring.add(semiring.times(F.col("a"), F.col("x"))).alias("v"))


def ewise_add(u: DataFrame, v: DataFrame, f: Callable[[Column, Column], Column] = lambda a, b: a + b) -> DataFrame:
    """Union of the indices; f where both have a value."""
    j = u.toDF("i", "a").withColumn("in_a", F.lit(True)).join(v.toDF("i", "b").withColumn("in_b", F.lit(True)), "i", "full_outer")
    return j.select("i", F.when(F.col("in_a") & F.col("in_b"), f(F.col("a"), F.col("b"))).when(F.col("in_a"), F.col("a")).otherwise(F.col("b")).alias("v"))


def ewise_mult(u: DataFrame, v: DataFrame, f: Callable[[Column, Column], Column] = lambda a, b: a * b) -> DataFrame:
    """Intersection of the indices."""
    return u.toDF("i", "a").join(v.toDF("i", "b"), "i").select("i", f(F.col("a"), F.col("b")).alias("v"))


def mask_out(u: DataFrame, v: DataFrame) -> DataFrame:
    """u without the indices of v."""
    return u.join(v.select("i"), "i", "left_anti")


def running(df: DataFrame, key: str, n: int, value: Column, chunks: int = 1024) -> DataFrame:
    """df with `upto`: the sum of value over all rows of smaller key (0 to n - 1, distinct). Sums within
    runs of keys, and over the few run totals: no window holds more than a run."""
    run = F.call_function("div", F.col(key), F.lit(max(1, -(-n // chunks))).cast("bigint"))
    rows = df.withColumn("_run", run).withColumn("_value", value)
    within = Window.partitionBy("_run").orderBy(key).rowsBetween(Window.unboundedPreceding, -1)
    before = Window.orderBy("_run").rowsBetween(Window.unboundedPreceding, -1)
    totals = rows.groupBy("_run").agg(F.sum("_value").alias("_total")).select("_run", F.coalesce(F.sum("_total").over(before), F.lit(0)).alias("_before"))
    told = rows.withColumn("_within", F.coalesce(F.sum("_value").over(within), F.lit(0))).join(F.broadcast(totals), "_run")  # as many rows as runs
    return told.select(*df.columns, (F.col("_before") + F.col("_within")).cast("bigint").alias("upto"))


def places(df: DataFrame, key: str, n: int) -> DataFrame:
    """df with `upto`: how many rows have a smaller key."""
    return running(df, key, n, F.lit(1))


def tiles(df: DataFrame, key: str, n: int, parts: int) -> DataFrame:
    """df with `tile`, 1 to parts: equal runs of the keys in order, the first ones a row longer."""
    rows = places(df, key, n).join(F.broadcast(df.agg(F.count(F.lit(1)).alias("_all"))))  # one row
    return rows.select(*df.columns, F.expr(f"""cast(if(upto < (_all % {parts}) * (_all div {parts} + 1), upto div (_all div {parts} + 1),
        _all % {parts} + (upto - (_all % {parts}) * (_all div {parts} + 1)) div greatest(_all div {parts}, 1)) + 1 as bigint)""").alias("tile"))
