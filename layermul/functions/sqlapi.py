"""The SQL surface: matrices as views, products as SQL text."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from layermul.functions.udfs import ExpandColumn
from layermul.matrix import SparseMatrix
from layermul.semiring import PLUS_TIMES, SEMIRINGS, Semiring
from layermul.sources.io import RmatSource


def product_sql(a: str, b: str, semiring: Semiring | str = PLUS_TIMES) -> str:
    """SQL of a product of two relations (i, j, v); runs on Spark and DuckDB alike."""
    s = SEMIRINGS[semiring] if isinstance(semiring, str) else semiring
    term = s.sql_times.format(a="a.v", b="b.v")
    return f"SELECT a.i, b.j, {s.sql_add.format(x=term)} AS v FROM {a} a JOIN {b} b ON a.j = b.i GROUP BY a.i, b.j"


def transpose_sql(a: str) -> str:
    return f"SELECT j AS i, i AS j, v FROM {a}"


def register(spark: SparkSession, **matrices: SparseMatrix) -> None:
    """Each matrix as a temporary view, the column-expanding table function, and the rmat source."""
    for name, m in matrices.items():
        m.df.createOrReplaceTempView(name)
    spark.udtf.register("expand_column", ExpandColumn)
    spark.dataSource.register(RmatSource)


def sql_multiply(spark: SparkSession, a: str, b: str, semiring: Semiring | str = PLUS_TIMES) -> DataFrame:
    return spark.sql(product_sql(a, b, semiring))
