"""Recursive random matrices whose every draw is a digest: equal in Spark, DuckDB and on any retry."""

from __future__ import annotations

from math import floor

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from layermul.matrix import SparseMatrix

# Quadrant probabilities and mean entries a row of the three classes.
CLASSES = {"skewed": ((0.57, 0.19, 0.19), 16), "community": ((0.6, 0.4 / 3, 0.4 / 3), 8), "uniform": ((0.25, 0.25, 0.25), 16)}


def cuts(cls: str) -> tuple[int, int, int]:
    """Where a 32-bit draw passes from one quadrant to the next."""
    a, b, c = CLASSES[cls][0]
    return floor(a * 2**32), floor((a + b) * 2**32), floor((a + b + c) * 2**32)


def rmat(spark: SparkSession, cls: str, scale: int, seed: int = 42) -> SparseMatrix:
    """2^scale x 2^scale; every draw picks a quadrant at each of `scale` levels, and repeated places
    add up. One expression a draw, so the only shuffle is the final count."""
    one, two, three = cuts(cls)
    n = CLASSES[cls][1] << scale
    step = f"""aggregate(sequence(0, {scale - 1}), named_struct('i', 0L, 'j', 0L), (s, l) -> transform(array(cast(conv(substr(md5(concat_ws(':', '{seed}', id, l)), 1, 8), 16, 10) as bigint)),
        h -> named_struct('i', s.i + if(h >= {two}, shiftleft(1L, l), 0L), 'j', s.j + if((h >= {one} AND h < {two}) OR h >= {three}, shiftleft(1L, l), 0L)))[0])"""
    drawn = spark.range(n).select(F.expr(step).alias("p")).select("p.i", "p.j")
    return SparseMatrix(drawn.groupBy("i", "j").agg(F.count(F.lit(1)).alias("v")), 1 << scale, 1 << scale)


def rmat_pair(spark: SparkSession, cls: str, scale: int, seeds: tuple[int, int] = (42, 43)) -> tuple[SparseMatrix, SparseMatrix]:
    """Two matrices of one class."""
    return rmat(spark, cls, scale, seeds[0]), rmat(spark, cls, scale, seeds[1])


def rmat_sql(cls: str, scale: int, seed: int = 42) -> str:
    one, two, three = cuts(cls)
    n = CLASSES[cls][1] << scale
    return f"""SELECT i, j, COUNT(*) AS v FROM (SELECT e, CAST(SUM(CASE WHEN h >= {two} THEN w ELSE 0 END) AS BIGINT) AS i,
        CAST(SUM(CASE WHEN (h >= {one} AND h < {two}) OR h >= {three} THEN w ELSE 0 END) AS BIGINT) AS j
        FROM (SELECT e, CAST(1 AS BIGINT) << l AS w, ('0x' || substr(md5('{seed}:' || e || ':' || l), 1, 8))::BIGINT AS h FROM range({n}) a(e), range({scale}) b(l)) GROUP BY e) GROUP BY 1, 2"""
