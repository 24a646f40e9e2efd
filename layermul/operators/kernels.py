"""Multiplication inside a cell: a heap over hypersparse columns, a dense accumulator, and the column
kernel in Spark's array functions. Values keep their type: whole, floating or decimal."""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.sql.types import DataType, LongType, StructField, StructType

from layermul.matrix import SparseMatrix
from layermul.plans.grid import Grid, col_block, fan_out, layer_of, row_block
from layermul.semiring import PLUS_TIMES, Semiring

_sum, _product = (lambda x, y: x + y), (lambda x, y: x * y)
_first, _second, _one = (lambda x, y: x), (lambda x, y: y), (lambda x, y: 1)
#: add and times of each semiring on single values.
PAIRS: dict[str, tuple[Callable, Callable]] = {
    "plus_times": (_sum, _product), "min_plus": (min, _sum), "max_min": (max, min), "or_and": (lambda x, y: x or y, lambda x, y: x and y), "min_second": (min, _second), "min_first": (min, _first),
    "max_second": (max, _second), "any_pair": (max, _one), "plus_pair": (_sum, _one), "plus_second": (_sum, _second), "max_times": (max, _product),
}
_repeat = lambda x, y: np.full(len(x), y)
_ones = lambda x, y: np.ones(len(x), np.int64)
#: The same on arrays: times of a column's values and one scalar.
ARRAYS: dict[str, tuple[Callable, Callable]] = {
    "plus_times": (np.add, np.multiply), "min_plus": (np.minimum, np.add), "max_min": (np.maximum, np.minimum), "or_and": (np.logical_or, np.logical_and), "min_second": (np.minimum, _repeat), "min_first": (np.minimum, _first),
    "max_second": (np.maximum, _repeat), "any_pair": (np.maximum, _ones), "plus_pair": (np.add, _ones), "plus_second": (np.add, _repeat), "max_times": (np.maximum, np.multiply),
}


@dataclass(frozen=True)
class Hypersparse:
    """Columns of a block: the nonempty ones (names, and where each starts), rows and values."""

    names: np.ndarray
    starts: np.ndarray
    rows: pa.ChunkedArray
    values: pa.ChunkedArray

    @classmethod
    def of(cls, t: pa.Table, column: str, row: str, value: str) -> Hypersparse:
        t = t.sort_by([(column, "ascending"), (row, "ascending")])
        names, starts = np.unique(t.column(column).to_numpy(), return_index=True)
        return cls(names, np.append(starts, t.num_rows), t.column(row), t.column(value))

    def find(self, wanted: np.ndarray) -> np.ndarray:
        """Place of each wanted column among the nonempty ones, -1 for empty ones."""
        if not len(self.names):
            return np.full(len(wanted), -1)
        at = np.minimum(np.searchsorted(self.names, wanted), len(self.names) - 1)
        return np.where(self.names[at] == wanted, at, -1)


def heap_columns(a: pa.Table, b: pa.Table, name: str) -> tuple[list, list, list]:
    """Each column of the result by a heap of one cursor for every entry of B's column, keyed by row;
    rows come out ascending and equal rows are combined as they come."""
    plus, times = PAIRS[name]
    one, two = Hypersparse.of(a, "k", "i", "a"), Hypersparse.of(b, "j", "k", "b")
    ai, av, bv = one.rows.to_pylist(), one.values.to_pylist(), two.values.to_pylist()
    at, starts = one.find(two.rows.to_numpy()).tolist(), one.starts.tolist()
    rows, cols, values = [], [], []
    for c, j in enumerate(two.names.tolist()):
        heap = [(ai[starts[at[x]]], x, starts[at[x]], starts[at[x] + 1]) for x in range(two.starts[c], two.starts[c + 1]) if at[x] >= 0]
        heapq.heapify(heap)
        last = None
        while heap:
            i, x, here, stop = heap[0]
            v = times(av[here], bv[x])
            if i == last:
                values[-1] = plus(values[-1], v)
            else:
                rows.append(i)
                cols.append(j)
                values.append(v)
                last = i
            if here + 1 < stop:
                heapq.heapreplace(heap, (ai[here + 1], x, here + 1, stop))
            else:
                heapq.heappop(heap)
    return rows, cols, values


def dense_columns(a: pa.Table, b: pa.Table, name: str) -> tuple[list, list, list]:
    """Each column of the result in an array as long as the cell has rows, cleared by its touched list."""
    plus, times = ARRAYS[name]
    rows, cols, values = [], [], []
    if not a.num_rows or not b.num_rows:
        return rows, cols, values
    one, two = Hypersparse.of(a, "k", "i", "a"), Hypersparse.of(b, "j", "k", "b")
    ai, av, bv = one.rows.to_numpy(), one.values.to_numpy(), two.values.to_numpy()
    at, low = one.find(two.rows.to_numpy()), int(ai.min())
    used = np.zeros(int(ai.max()) - low + 1, bool)
    scratch = np.zeros(len(used), np.asarray(times(av[:1], bv[0])).dtype)
    for c, j in enumerate(two.names.tolist()):
        touched = []
        for x in range(two.starts[c], two.starts[c + 1]):
            if at[x] < 0:
                continue
            s = slice(one.starts[at[x]], one.starts[at[x] + 1])
            place = ai[s] - low  # distinct within a column of A
            v = times(av[s], bv[x])
            scratch[place] = np.where(used[place], plus(scratch[place], v), v)
            used[place] = True
            touched.append(place)
        if touched:
            place = np.unique(np.concatenate(touched))
            rows += (place + low).tolist()
            cols += [j] * len(place)
            values += scratch[place].tolist()
            used[place] = False
    return rows, cols, values


def triples_of(kind: DataType) -> StructType:
    return StructType([StructField("i", LongType()), StructField("j", LongType()), StructField("v", kind)])


def product_type(a: SparseMatrix, b: SparseMatrix, semiring: Semiring) -> DataType:
    """Type of a product's values; only the plan is analysed."""
    points = a.df.toDF("i", "k", "a").join(b.df.toDF("k", "j", "b"), "k")
    return points.agg(semiring.add(semiring.times(F.col("a"), F.col("b"))).alias("v")).schema["v"].dataType


def cell_kernel(a: SparseMatrix, b: SparseMatrix, grid: Grid, kernel: str = "heap", semiring: Semiring = PLUS_TIMES, parts: int = 1) -> DataFrame:
    """(i, j, v) of every cell by a kernel, partial results of several layers not yet merged. parts
    splits each cell by output column; the cell's operands must fit one task."""
    columns = {"heap": heap_columns, "acc": dense_columns}[kernel]
    name, result = semiring.name, product_type(a, b, semiring)
    arrow = pa.schema([("i", pa.int64()), ("j", pa.int64()), ("v", to_arrow_type(result))])
    k = F.col("k")
    part = F.pmod(F.col("j"), F.lit(parts).cast("bigint"))
    left = a.df.toDF("i", "k", "a").withColumn("gi", row_block(F.col("i"), a.nrows, grid)).withColumn("gl", layer_of(k, a.ncols, grid))
    left = fan_out(fan_out(left, grid.pc, "gj"), parts, "part")
    right = b.df.toDF("k", "j", "b").withColumn("gj", col_block(F.col("j"), b.ncols, grid)).withColumn("gl", layer_of(k, a.ncols, grid)).withColumn("part", part)
    right = fan_out(right, grid.pr, "gi")
    keys = ["gi", "gj", "gl", "part"]

    def run(one: pa.Table, two: pa.Table) -> pa.Table:
        return pa.table([pa.array(x, t) for x, t in zip(columns(one, two, name), arrow.types, strict=True)], schema=arrow)

    return left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(run, triples_of(result))


def _by_kernel(a: SparseMatrix, b: SparseMatrix, grid: Grid, kernel: str, semiring: Semiring, parts: int) -> SparseMatrix:
    made = cell_kernel(a, b, grid, kernel, semiring, parts)
    return SparseMatrix(made if grid.pl == 1 else made.groupBy("i", "j").agg(semiring.merge(F.col("v")).alias("v")), a.nrows, b.ncols)


def heap_kernel(a: SparseMatrix, b: SparseMatrix, grid: Grid = Grid(), semiring: Semiring = PLUS_TIMES, parts: int = 1) -> SparseMatrix:
    """Product by the heap kernel; parts are disjoint sets of output columns."""
    return _by_kernel(a, b, grid, "heap", semiring, parts)


def dense_acc_kernel(a: SparseMatrix, b: SparseMatrix, grid: Grid = Grid(), semiring: Semiring = PLUS_TIMES, parts: int = 1) -> SparseMatrix:
    return _by_kernel(a, b, grid, "acc", semiring, parts)


def column_kernel_sql(a: SparseMatrix, b: SparseMatrix) -> SparseMatrix:
    """Column by column in array functions: A's columns that B's column selects are scaled, put
    together, sorted, and each run of one row folded where it stands. One array per output column;
    plus-times."""
    from .layout import to_dcsc

    kind = product_type(a, b, PLUS_TIMES).simpleString()
    cols = to_dcsc(a).df.select(F.col("j").alias("k"), "entries")
    picked = b.df.toDF("k", "j", "b").join(cols, "k").select("j", F.transform("entries", lambda e: F.struct(e["i"].alias("i"), (e["v"] * F.col("b")).alias("v"))).alias("part"))
    merged = picked.groupBy("j").agg(F.array_sort(F.flatten(F.collect_list("part"))).alias("all"))
    starts = merged.select("j", "all", F.expr("filter(transform(all, (e, x) -> if(x = 0 OR all[x - 1].i <> e.i, x + 1, 0)), s -> s > 0)").alias("starts"))
    stops = "concat(slice(starts, 2, size(starts)), array(size(all) + 1))"
    runs = f"""zip_with(starts, {stops}, (s, e) -> named_struct('i', all[s - 1].i,
        'v', aggregate(slice(all, s, e - s), cast(0 as {kind}), (t, x) -> cast(t + x.v as {kind}))))"""
    return SparseMatrix(starts.select("j", F.expr(f"explode({runs})").alias("r")).select("r.i", "j", "r.v"), a.nrows, b.ncols)


def sorted_triples(m: SparseMatrix, parts: int | None = None) -> DataFrame:
    """Entries in order of column and row, dealt out by column range."""
    df = m.df.repartitionByRange(parts, "j") if parts else m.df.repartitionByRange("j")
    return df.sortWithinPartitions("j", "i")


def out_of_order(df: Iterator | DataFrame) -> DataFrame:
    """How many rows stand before their predecessor within the partitions of a sorted frame."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, bad = None, 0
        for batch in batches:
            for key in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                bad += last is not None and key < last
                last = key
        yield pa.RecordBatch.from_arrays([pa.array([bad], pa.int64())], ["violations"])

    return df.select("j", "i").mapInArrow(run, "violations bigint").agg(F.coalesce(F.sum("violations"), F.lit(0)).cast("bigint").alias("violations"))
