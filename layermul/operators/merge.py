"""Merging lists of triples: combine while merging, or merge first and reduce after."""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from layermul.matrix import SparseMatrix
from layermul.plans.grid import Grid, col_block, layer_of, row_block
from layermul.semiring import PLUS_TIMES, Semiring

from .kernels import PAIRS, triples_of
from .vector import running


def stage_lists(a: SparseMatrix, b: SparseMatrix, k: int) -> DataFrame:
    """(list, i, j, v): the k partial results of a product whose inner index is cut into k runs."""
    one, two = a.df.toDF("i", "k", "a"), b.df.toDF("k", "j", "b")
    points = one.join(two, "k").withColumn("list", layer_of(F.col("k"), a.ncols, Grid(1, 1, k)).cast("bigint"))
    return points.groupBy("list", "i", "j").agg(F.sum(F.col("a") * F.col("b")).alias("v"))


def union_of(lists: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, lists)


def kway_merge(lists: DataFrame, semiring: Semiring = PLUS_TIMES) -> DataFrame:
    """One list (i, j, v): equal entries combined on the way, in the partial pass before the exchange
    and in the final one after it. The same routine merges stages of a layer and layers of a fiber."""
    return lists.groupBy("j", "i").agg(semiring.merge(F.col("v")).alias("v")).select("i", "j", "v")


merge_layer = merge_fiber = kway_merge


def kway_merge_heap(lists: DataFrame, threads: int = 4, semiring: Semiring = PLUS_TIMES) -> DataFrame:
    """The kernel form: four column ranges for each of `threads` workers, cut where samples of the entries
    say that their numbers are alike. A range holds a sorted piece of each of the k lists; a heap of
    k cursors merges them, and equal entries are combined as they come. A range must fit one task."""
    plus, kind = PAIRS[semiring.name][0], lists.agg(semiring.merge(F.col("v")).alias("v")).schema["v"].dataType
    arrow = pa.schema([("i", pa.int64()), ("j", pa.int64()), ("v", to_arrow_type(kind))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = list(batches)
        if not pieces:
            return
        held = pa.Table.from_batches(pieces)
        name, j, i, v = (held.column(c).to_pylist() for c in range(4))
        cuts = [0, *(x for x in range(1, len(name)) if name[x] != name[x - 1]), len(name)]
        heap = [(j[s], i[s], s, e) for s, e in zip(cuts, cuts[1:], strict=False)]
        heapq.heapify(heap)
        out: tuple[list, list, list] = ([], [], [])
        while heap:
            col, row, at, stop = heap[0]
            if out[0] and out[0][-1] == row and out[1][-1] == col:
                out[2][-1] = plus(out[2][-1], v[at])
            else:
                for x, y in zip(out, (row, col, v[at]), strict=True):
                    x.append(y)
            if at + 1 < stop:
                heapq.heapreplace(heap, (j[at + 1], i[at + 1], at + 1, stop))
            else:
                heapq.heappop(heap)
        yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(out, arrow.types, strict=True)], schema=arrow)

    return lists.select("list", "j", "i", "v").repartitionByRange(4 * threads, "j").sortWithinPartitions("list", "j", "i").mapInArrow(run, triples_of(kind))


def merge_then_reduce(lists: DataFrame, semiring: Semiring = PLUS_TIMES) -> DataFrame:
    """Two passes, for comparison: all entries into one sorted list, then runs of equal entries found
    by looking back and reduced."""
    order = Window.partitionBy("j").orderBy("i", "list")
    flagged = lists.withColumn("new", (F.coalesce(F.lag("i").over(order), F.lit(-1)) != F.col("i")).cast("int"))
    runs = flagged.withColumn("run", F.sum("new").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    return runs.groupBy("j", "run").agg(F.min("i").alias("i"), semiring.merge(F.col("v")).alias("v")).select("i", "j", "v")


def equal_work_cuts(m: SparseMatrix, parts: int) -> DataFrame:
    """(part, lo, hi, nnz): column ranges of like numbers of entries, from running sums of column sizes."""
    per = running(m.df.groupBy("j").agg(F.count(F.lit(1)).alias("n")), "j", m.ncols, F.col("n"))
    total = m.df.agg(F.count(F.lit(1)).alias("total"))
    part = F.call_function("div", F.col("upto") * parts, F.col("total"))
    return per.join(F.broadcast(total)).withColumn("part", part).groupBy("part").agg(F.min("j").alias("lo"), F.max("j").alias("hi"), F.sum("n").alias("nnz"))  # one row


def cell_stage_lists(a: SparseMatrix, b: SparseMatrix, grid: Grid, cell: tuple[int, int] = (0, 0)) -> DataFrame:
    """(list, i, j, v): what one cell of a grid of one layer has to merge, a list for each stage."""
    rows = a.df.where(row_block(F.col("i"), a.nrows, grid) == cell[0])
    cols = b.df.where(col_block(F.col("j"), b.ncols, grid) == cell[1])
    return stage_lists(a.with_df(rows), b.with_df(cols), grid.pc)
