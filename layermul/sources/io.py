"""Reading and writing matrices: coordinate text, CSV, JSON lines, Parquet by block, bucketed tables,
and the random generator as a Spark data source."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from layermul.matrix import SparseMatrix
from layermul.plans.grid import Grid, owner_a


def write_coo_text(m: SparseMatrix, path: str) -> None:
    """Lines "i j v", 1-based, with the dimensions in a comment line of their own file part."""
    spark = m.df.sparkSession
    head = spark.createDataFrame([(f"% {m.nrows} {m.ncols}",)], "value string").coalesce(1)
    m.df.select(F.concat_ws(" ", (F.col("i") + 1).cast("string"), (F.col("j") + 1).cast("string"), F.col("v").cast("string")).alias("value")).unionByName(head).write.text(path)


def read_coo_text(spark: SparkSession, path: str, kind: str = "bigint", nrows: int | None = None, ncols: int | None = None) -> SparseMatrix:
    """Lines that aren't three numbers are left out; dimensions from the first comment that has two."""
    lines = spark.read.text(path)
    if nrows is None or ncols is None:
        head = lines.where(F.col("value").rlike(r"^%\s*\d+\s+\d+")).select(F.regexp_extract("value", r"(\d+)\s+(\d+)", 1).cast("bigint").alias("m"), F.regexp_extract("value", r"(\d+)\s+(\d+)", 2).cast("bigint").alias("n")).first()
        nrows, ncols = (nrows or head["m"], ncols or head["n"]) if head else (nrows, ncols)
    part = F.split(F.trim("value"), r"\s+")
    cells = lines.where(~F.col("value").startswith("%")).where(F.size(part) >= 3).select((F.expr(f"try_cast(split(trim(value), '\\\\s+')[0] as bigint)") - 1).alias("i"), (F.expr("try_cast(split(trim(value), '\\\\s+')[1] as bigint)") - 1).alias("j"), F.expr(f"try_cast(split(trim(value), '\\\\s+')[2] as {kind})").alias("v"))
    return SparseMatrix.of(cells.where("i IS NOT NULL AND j IS NOT NULL AND v IS NOT NULL"), nrows, ncols)


def write_csv(m: SparseMatrix, path: str) -> None:
    m.df.write.option("header", True).csv(path)


def read_csv(spark: SparkSession, path: str, nrows: int | None = None, ncols: int | None = None) -> SparseMatrix:
    return SparseMatrix.of(spark.read.schema("i bigint, j bigint, v bigint").option("header", True).csv(path), nrows, ncols)


def write_json(m: SparseMatrix, path: str) -> None:
    m.df.write.json(path)


def read_json(spark: SparkSession, path: str, nrows: int | None = None, ncols: int | None = None) -> SparseMatrix:
    return SparseMatrix.of(spark.read.schema("i bigint, j bigint, v bigint").json(path), nrows, ncols)


def write_blocks(m: SparseMatrix, path: str, grid: Grid) -> None:
    """Parquet in folders by block row and column: reading a block prunes all others."""
    gi, gj, _ = owner_a(F.col("i"), F.col("j"), m.nrows, m.ncols, grid)
    m.df.withColumn("gi", gi).withColumn("gj", gj).repartition("gi", "gj").sortWithinPartitions("gi", "gj", "j", "i").write.partitionBy("gi", "gj").parquet(path)


def read_blocks(spark: SparkSession, path: str, nrows: int, ncols: int, rows: list[int] | None = None, cols: list[int] | None = None) -> SparseMatrix:
    df = spark.read.schema("i bigint, j bigint, v bigint, gi bigint, gj bigint").parquet(path)
    for name, wanted in (("gi", rows), ("gj", cols)):
        df = df if wanted is None else df.where(F.col(name).isin(wanted))
    return SparseMatrix(df.select("i", "j", "v"), nrows, ncols)


def save_bucketed(m: SparseMatrix, name: str, buckets: int = 16, by: str = "j", path: str | None = None) -> None:
    """A table bucketed and sorted by an index: products on it join without a shuffle of this side."""
    writer = m.df.write.bucketBy(buckets, by).sortBy(by, "i" if by == "j" else "j").mode("overwrite")
    (writer.option("path", path) if path else writer).saveAsTable(name)


def load_bucketed(spark: SparkSession, name: str, nrows: int, ncols: int) -> SparseMatrix:
    return SparseMatrix(spark.table(name).select("i", "j", "v"), nrows, ncols)


class RmatSource(DataSource):
    """spark.read.format("rmat").option("class", ...).option("scale", ...).load(): the draws (e, i, j),
    repeats not yet added up."""

    @classmethod
    def name(cls) -> str:
        return "rmat"

    def schema(self) -> str:
        return "e bigint, i bigint, j bigint"

    def reader(self, schema) -> DataSourceReader:
        return _RmatReader(self.options)


class _RmatReader(DataSourceReader):
    def __init__(self, options):
        self.cls, self.scale = options.get("class", "skewed"), int(options.get("scale", "8"))
        self.seed, self.parts = int(options.get("seed", "42")), int(options.get("partitions", "8"))

    def partitions(self):
        return [InputPartition(p) for p in range(self.parts)]

    def read(self, partition):
        from hashlib import md5

        from layermul.sources.generators import CLASSES, cuts

        one, two, three = cuts(self.cls)
        n = CLASSES[self.cls][1] << self.scale
        for e in range(partition.value * n // self.parts, (partition.value + 1) * n // self.parts):
            i = j = 0
            for level in range(self.scale):
                h = int(md5(f"{self.seed}:{e}:{level}".encode()).hexdigest()[:8], 16)
                i |= (h >= two) << level
                j |= (one <= h < two or h >= three) << level
            yield e, i, j
