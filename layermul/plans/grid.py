"""Process grids: which cell owns an entry, and how entries reach the cells that need them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Grid:
    """pr x pc cells in each of pl layers."""

    pr: int = 1
    pc: int = 1
    pl: int = 1

    @property
    def cells(self) -> int:
        return self.pr * self.pc * self.pl


def _ceil(a: int, b: int) -> int:
    return max(1, -(-a // b))


def _div(x: Column, n: int) -> Column:
    """Integer quotient of numbers from 0 on."""
    return F.call_function("div", x, F.lit(n).cast("bigint"))


def row_block(i: Column, nrows: int, grid: Grid) -> Column:
    return _div(i, _ceil(nrows, grid.pr))


def col_block(j: Column, ncols: int, grid: Grid) -> Column:
    return _div(j, _ceil(ncols, grid.pc))


def slice_of(j: Column, ncols: int, grid: Grid) -> Column:
    """Which of the pl slices of its column block an index lies in."""
    width = _ceil(ncols, grid.pc)
    return _div(F.pmod(j, F.lit(width).cast("bigint")), _ceil(width, grid.pl))


def layer_of(k: Column, inner: int, grid: Grid) -> Column:
    """The layer that multiplies inner index k; one formula for A's columns and B's rows."""
    return slice_of(k, inner, grid)


def panel_of(k: Column, inner: int, grid: Grid, block: int | None) -> Column:
    """Stage and panel of an inner index: its column block of A, and the block-wide strip inside the slice."""
    width = _ceil(inner, grid.pc)
    strip = _ceil(width, grid.pl)
    step = strip if block is None else min(block, strip)
    local = F.pmod(F.pmod(k, F.lit(width).cast("bigint")), F.lit(strip).cast("bigint"))
    return _div(k, width) * _ceil(strip, step) + _div(local, step)


def owner_a(i: Column, j: Column, nrows: int, ncols: int, grid: Grid) -> tuple[Column, Column, Column]:
    """(gi, gj, gl): blocks of rows and columns, the columns of a block sliced into layers."""
    return row_block(i, nrows, grid), col_block(j, ncols, grid), slice_of(j, ncols, grid)


owner_b = owner_c = owner_a


def owner_bhat(k: Column, j: Column, inner: int, ncols: int, grid: Grid) -> tuple[Column, Column, Column]:
    """(gi, gj, gl) of B after it has been dealt to the layers: its rows decide the layer."""
    return row_block(k, inner, grid), col_block(j, ncols, grid), layer_of(k, inner, grid)


def _murmur_int(x: int, seed: int = 42) -> int:
    """Spark's hash() of one INT."""
    m = 0xFFFFFFFF
    rot = lambda v, r: ((v << r) | (v >> (32 - r))) & m
    k = rot(x * 0xCC9E2D51 & m, 15) * 0x1B873593 & m
    h = (rot(seed ^ k, 13) * 5 + 0xE6546B64) & m
    h ^= 4
    h = (h ^ h >> 16) * 0x85EBCA6B & m
    h = (h ^ h >> 13) * 0xC2B2AE35 & m
    h ^= h >> 16
    return h - (1 << 32) if h >> 31 else h


def partition_keys(n: int) -> list[int]:
    """n integers of which the p-th falls into partition p of n hash partitions."""
    out: dict[int, int] = {}
    x = 0
    while len(out) < n:
        out.setdefault(_murmur_int(x) % n, x)
        x += 1
    return [out[p] for p in range(n)]


@dataclass(frozen=True)
class GridConfig:
    """workers processes of `threads` threads each, in `layers` layers: the pair that is tuned."""

    workers: int
    layers: int = 1
    threads: int = 1

    @property
    def grid(self) -> Grid:
        """The squarest grid of at most workers / layers cells in each layer."""
        cells = max(1, self.workers // self.layers)
        pr = int(cells**0.5)
        return Grid(pr, max(1, cells // pr), self.layers)


def refined(grid: Grid, n: int) -> Grid:
    """A grid of one layer cut on until it has n cells at least, the coarser side first."""
    pr, pc = grid.pr, grid.pc
    while pr * pc < n:
        pr, pc = (pr, 2 * pc) if pc <= pr else (2 * pr, pc)
    return Grid(pr, pc, grid.pl)


def threads_per_cell(spark: SparkSession, grid: Grid) -> int:
    """Sub-splits of a cell, so that all cells together fill the session's shuffle partitions: with
    fewer, Spark would deal out anew to gain parallelism."""
    return max(1, -(-int(spark.conf.get("spark.sql.shuffle.partitions")) // grid.cells))


def to_cells(df: DataFrame, gi: Column, gj: Column, gl: Column, part: Column, grid: Grid, threads: int) -> DataFrame:
    """df with the column cell, an integer whose hash partition is the entry's cell and sub-split `part`,
    dealt out by it."""
    keys = F.array(*[F.lit(x) for x in partition_keys(grid.cells * threads)])
    number = ((gi * grid.pc + gj) * grid.pl + gl) * threads + part
    return df.withColumn("cell", F.element_at(keys, (number + 1).cast("int"))).repartition(grid.cells * threads, "cell")


def fan_out(df: DataFrame, copies: int, name: str) -> DataFrame:
    """Every row once for each cell of its grid row or column."""
    if copies == 1:
        return df.withColumn(name, F.lit(0).cast("bigint"))
    return df.withColumn(name, F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(copies - 1).cast("bigint"))))
