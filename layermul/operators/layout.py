"""Column layouts: only the nonempty columns, with an index, or every column."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from layermul.matrix import SparseMatrix


@dataclass(frozen=True)
class Dcsc:
    """One row (j, entries) for each nonempty column, or for each chunk of a column of more than
    `longest` entries; entries is array<struct<i, v>> sorted by i."""

    df: DataFrame
    nrows: int
    ncols: int

    def columns(self, lo: int, hi: int) -> Dcsc:
        """Columns lo to hi - 1."""
        return Dcsc(self.df.where((F.col("j") >= lo) & (F.col("j") < hi)), self.nrows, self.ncols)

    def matrix(self) -> SparseMatrix:
        return SparseMatrix(self.df.select("j", F.explode("entries").alias("e")).select("e.i", "j", "e.v"), self.nrows, self.ncols)


def to_dcsc(m: SparseMatrix, longest: int | None = None) -> Dcsc:
    """longest: rows of a chunk's index range, which keeps hub columns from becoming one row."""
    keys = ["j"] if longest is None else ["j", F.call_function("div", F.col("i"), F.lit(longest).cast("bigint")).alias("chunk")]
    return Dcsc(m.df.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("i", "v"))).alias("entries")), m.nrows, m.ncols)


def every_column(m: SparseMatrix) -> DataFrame:
    """(j, entries) with a row for every column, empty ones too: the layout measured for contrast."""
    return m.df.sparkSession.range(m.ncols).select(F.col("id").alias("j")).join(to_dcsc(m).df, "j", "left").select("j", F.coalesce("entries", F.array().cast("array<struct<i:bigint,v:bigint>>")).alias("entries"))


def aux_index(d: Dcsc, width: int) -> DataFrame:
    """(chunk, n, lo, hi): the nonempty columns of each run of `width` columns."""
    chunk = F.call_function("div", F.col("j"), F.lit(width).cast("bigint"))
    return d.df.groupBy(chunk.alias("chunk")).agg(F.countDistinct("j").alias("n"), F.min("j").alias("lo"), F.max("j").alias("hi"))
