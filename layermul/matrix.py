"""Sparse matrices as tables of stored entries (i, j, v), 0-based, with their dimensions beside them."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class SparseMatrix:
    """df has exactly the columns i, j, v and one row per stored entry. A stored zero is an entry."""

    df: DataFrame
    nrows: int
    ncols: int

    # --- making ---

    @classmethod
    def of(cls, df: DataFrame, nrows: int | None = None, ncols: int | None = None) -> SparseMatrix:
        """From columns i, j, v. Dimensions that aren't given are one more than the largest index."""
        df = df.select(F.col("i").cast("bigint"), F.col("j").cast("bigint"), "v")
        if nrows is None or ncols is None:
            top = df.agg(F.max("i").alias("i"), F.max("j").alias("j")).first()
            nrows = nrows if nrows is not None else (-1 if top["i"] is None else top["i"]) + 1
            ncols = ncols if ncols is not None else (-1 if top["j"] is None else top["j"]) + 1
        return cls(df, nrows, ncols)

    @classmethod
    def from_duplicates(cls, df: DataFrame, nrows: int | None = None, ncols: int | None = None) -> SparseMatrix:
        """Repeated (i, j) are summed."""
        return cls.of(df.groupBy("i", "j").agg(F.sum("v").alias("v")), nrows, ncols)

    @classmethod
    def rows_of(cls, spark: SparkSession, entries: Iterable[tuple], nrows: int, ncols: int, kind: str = "bigint") -> SparseMatrix:
        return cls(spark.createDataFrame(list(entries), f"i bigint, j bigint, v {kind}"), nrows, ncols)

    @classmethod
    def eye(cls, spark: SparkSession, n: int) -> SparseMatrix:
        return cls(spark.range(n).select(F.col("id").alias("i"), F.col("id").alias("j"), F.lit(1).cast("bigint").alias("v")), n, n)

    def with_df(self, df: DataFrame) -> SparseMatrix:
        return SparseMatrix(df.select("i", "j", "v"), self.nrows, self.ncols)

    # --- one operand ---

    def transpose(self) -> SparseMatrix:
        return SparseMatrix(self.df.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), self.ncols, self.nrows)

    t = property(transpose)

    def apply(self, f: Callable[[Column], Column]) -> SparseMatrix:
        return self.with_df(self.df.withColumn("v", f(F.col("v"))))

    def scale(self, s) -> SparseMatrix:
        return self.apply(lambda v: v * s)

    def where(self, condition) -> SparseMatrix:
        return self.with_df(self.df.where(condition))

    def drop_zeros(self) -> SparseMatrix:
        return self.where("v <> 0")

    def diagonal(self) -> SparseMatrix:
        return self.where("i = j")

    def off_diagonal(self) -> SparseMatrix:
        return self.where("i <> j")

    def tril(self, strict: bool = True) -> SparseMatrix:
        return self.where("i > j" if strict else "i >= j")

    def triu(self, strict: bool = True) -> SparseMatrix:
        return self.where("i < j" if strict else "i <= j")

    def extract(self, rows: tuple[int, int], cols: tuple[int, int]) -> SparseMatrix:
        """Half-open ranges, renumbered from 0; the ranges reach the scan."""
        (a, b), (c, d) = rows, cols
        df = self.df.where((F.col("i") >= a) & (F.col("i") < b) & (F.col("j") >= c) & (F.col("j") < d))
        return SparseMatrix(df.select((F.col("i") - a).alias("i"), (F.col("j") - c).alias("j"), "v"), b - a, d - c)

    def assign(self, rows: tuple[int, int], cols: tuple[int, int], block: SparseMatrix) -> SparseMatrix:
        (a, b), (c, d) = rows, cols
        rest = self.df.where(~((F.col("i") >= a) & (F.col("i") < b) & (F.col("j") >= c) & (F.col("j") < d)))
        return self.with_df(rest.unionByName(block.df.select((F.col("i") + a).alias("i"), (F.col("j") + c).alias("j"), "v")))

    def pattern(self) -> SparseMatrix:
        return self.apply(lambda v: F.lit(1).cast("bigint"))

    def reduce_rows(self, op: Callable[[Column], Column] = F.sum) -> DataFrame:
        return self.df.groupBy("i").agg(op("v").alias("v"))

    def reduce_cols(self, op: Callable[[Column], Column] = F.sum) -> DataFrame:
        return self.t.reduce_rows(op)

    def nnz(self) -> int:
        return self.df.count()

    def trace(self) -> DataFrame:
        return self.diagonal().df.agg(F.coalesce(F.sum("v"), F.lit(0)).cast("bigint").alias("v"))

    # --- two operands ---

    def ewise_add(self, other: SparseMatrix, f: Callable[[Column, Column], Column] = lambda a, b: a + b) -> SparseMatrix:
        """Union of the patterns; f where both have an entry."""
        a, b = self.df.toDF("i", "j", "a"), other.df.toDF("i", "j", "b")
        both = F.col("in_a") & F.col("in_b")
        joined = a.withColumn("in_a", F.lit(True)).join(b.withColumn("in_b", F.lit(True)), ["i", "j"], "full_outer")
        return self.with_df(joined.select("i", "j", F.when(both, f(F.col("a"), F.col("b"))).when(F.col("in_a"), F.col("a")).otherwise(F.col("b")).alias("v")))

    add = ewise_add

    def subtract(self, other: SparseMatrix) -> SparseMatrix:
        return self.ewise_add(other.scale(-1))

    def ewise_mult(self, other: SparseMatrix, f: Callable[[Column, Column], Column] = lambda a, b: a * b) -> SparseMatrix:
        """Intersection of the patterns."""
        joined = self.df.toDF("i", "j", "a").join(other.df.toDF("i", "j", "b"), ["i", "j"])
        return self.with_df(joined.select("i", "j", f(F.col("a"), F.col("b")).alias("v")))

    def mask(self, m: SparseMatrix, complement: bool = False) -> SparseMatrix:
        return self.with_df(self.df.join(m.df.select("i", "j"), ["i", "j"], "left_anti" if complement else "left_semi"))

    def kron(self, small: SparseMatrix) -> SparseMatrix:
        """Each entry times a small matrix, which is carried to every task."""
        b = F.broadcast(small.df.select(F.col("i").alias("bi"), F.col("j").alias("bj"), F.col("v").alias("bv")))
        df = self.df.join(b).select((F.col("i") * small.nrows + F.col("bi")).alias("i"), (F.col("j") * small.ncols + F.col("bj")).alias("j"), (F.col("v") * F.col("bv")).alias("v"))
        return SparseMatrix(df, self.nrows * small.nrows, self.ncols * small.ncols)

    # --- renumbering ---

    def permute(self, perm: AffinePermutation) -> SparseMatrix:
        """Rows and columns of a square matrix by one bijection, without a shuffle."""
        return self.with_df(self.df.select(perm.apply(F.col("i")).alias("i"), perm.apply(F.col("j")).alias("j"), "v"))

    def unpermute(self, perm: AffinePermutation) -> SparseMatrix:
        return self.permute(perm.inverse())

    def split_diagonal(self) -> tuple[SparseMatrix, SparseMatrix]:
        return self.diagonal(), self.off_diagonal()


@dataclass(frozen=True)
class AffinePermutation:
    """x -> (step * x + shift) mod n, with step prime to n."""

    n: int
    step: int
    shift: int

    @classmethod
    def near(cls, n: int, step: int = 1237, shift: int = 11) -> AffinePermutation:
        from math import gcd

        while gcd(step, n) != 1:
            step += 1
        return cls(n, step, shift)

    def apply(self, x: Column) -> Column:
        return F.pmod(x * F.lit(self.step).cast("bigint") + self.shift, F.lit(self.n).cast("bigint"))

    def inverse(self) -> AffinePermutation:
        back = pow(self.step, -1, self.n) if self.n > 1 else 0
        return AffinePermutation(self.n, back, -back * self.shift % max(self.n, 1))


def digest_permutation(spark: SparkSession, n: int, seed: int = 42) -> DataFrame:
    """(x, p): a bijection of 0 to n - 1 that keeps no structure: p is the place of x's digest among all.
    Digests are ranked within runs of a common beginning, and the runs by their totals."""
    digest = F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("id").cast("string")))
    rows = spark.range(n).select(F.col("id").alias("x"), digest.alias("d"), F.substring(digest, 1, 3).alias("run"))
    before = Window.orderBy("run").rowsBetween(Window.unboundedPreceding, -1)  # 4096 rows at most
    runs = rows.groupBy("run").agg(F.count(F.lit(1)).alias("n")).select("run", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    place = F.row_number().over(Window.partitionBy("run").orderBy("d", "x")) - 1
    return rows.withColumn("place", place).join(F.broadcast(runs), "run").select("x", (F.col("start") + F.col("place")).cast("bigint").alias("p"))


def permute_by(m: SparseMatrix, table: DataFrame) -> SparseMatrix:
    """Rows and columns of a square matrix renumbered by a table (x, p)."""
    rows, cols = table.toDF("i", "pi"), table.toDF("j", "pj")
    return m.with_df(m.df.join(rows, "i").join(cols, "j").select(F.col("pi").alias("i"), F.col("pj").alias("j"), "v"))
