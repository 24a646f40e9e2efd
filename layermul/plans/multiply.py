"""Physical plans of C = A B: Spark's own, one-, two- and three-dimensional.

All compute join on the inner index, product, combine per output entry; they differ in where entries
travel. The layered plan (grid3d) with one layer is the two-dimensional one, with one cell per layer
it is Spark's own.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from layermul.matrix import SparseMatrix
from layermul.semiring import PLUS_TIMES, Semiring
from layermul.session import configure, materialize

from .grid import Grid, col_block, fan_out, layer_of, panel_of, partition_keys, refined, row_block, slice_of, threads_per_cell, to_cells

#: Entries of an operand that the broadcast hint may send whole to all workers, by way of the driver.
HINTED_ENTRIES = 2_000_000
#: Pairs of an inner index and a worker that wants it which may be sent to all workers.
WANTED_PAIRS = 4_000_000


class TooMuchWork(ValueError):
    """The product would take more scalar products than allowed."""


def _sides(a: SparseMatrix, b: SparseMatrix) -> tuple[DataFrame, DataFrame]:
    if a.ncols != b.nrows:
        raise ValueError(f"inner dimensions differ: {a.ncols} and {b.nrows}")
    return a.df.toDF("i", "k", "a"), b.df.toDF("k", "j", "b")


def _combined(points: DataFrame, semiring: Semiring, keys=("i", "j")) -> DataFrame:
    return points.groupBy(*keys).agg(semiring.add(semiring.times(F.col("a"), F.col("b"))).alias("v"))


def catalyst(a: SparseMatrix, b: SparseMatrix, semiring: Semiring = PLUS_TIMES, hint: str | None = None) -> SparseMatrix:
    """Join on the inner index and aggregate, as Spark plans it; hint: merge, shuffle_hash or broadcast. An
    operand of more than HINTED_ENTRIES is not broadcast but shuffled."""
    left, right = _sides(a, b)
    if hint == "broadcast" and b.nnz() > HINTED_ENTRIES:
        hint = "shuffle_hash"
    right = right.hint(hint) if hint else right
    return SparseMatrix(_combined(left.join(right, "k"), semiring), a.nrows, b.ncols)


def oned(a: SparseMatrix, b: SparseMatrix, semiring: Semiring = PLUS_TIMES, by: str = "row", parts: int | None = None, rowmap: str = "random", broadcast: bool = False) -> SparseMatrix:
    """One-dimensional: workers own rows of A and C (by row; only B travels), columns of B and C (by
    col), or parts of the inner index (by inner). rowmap: random deals rows by hash, block by range.
    broadcast: B goes whole to all workers, for a B whose size the caller has checked."""
    if by == "inner":
        return grid3d(a, b, Grid(1, 1, parts or 8), semiring)
    if by == "col":
        return oned(b.t, a.t, _swapped(semiring), "row", parts, rowmap, broadcast).t
    left, right = _sides(a, b)
    if broadcast:
        return SparseMatrix(_combined(left.join(F.broadcast(right), "k"), semiring), a.nrows, b.ncols)
    spark = configure(a.df.sparkSession)
    # as many workers as partitions at least, else Spark would deal out anew
    n = max(parts or 1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    keys = F.array(*[F.lit(x) for x in partition_keys(n)])
    worker = F.pmod(F.hash("i"), F.lit(n)) if rowmap == "random" else row_block(F.col("i"), a.nrows, Grid(n, 1, 1)).cast("int")
    left = left.withColumn("w", F.element_at(keys, worker + 1))
    # B's row k goes to the workers whose rows of A use it; products stay with A's rows
    wanted = left.groupBy("k").agg(F.collect_set("w").alias("ws"))
    wanted = F.broadcast(wanted) if a.ncols * n <= WANTED_PAIRS else wanted
    fetched = right.join(wanted, "k").select("k", "j", "b", F.explode("ws").alias("w"))
    points = left.repartition(n, "w").join(fetched.repartition(n, "w"), ["w", "k"])
    return SparseMatrix(_combined(points, semiring, ("w", "i", "j")).select("i", "j", "v"), a.nrows, b.ncols)


def _swapped(s: Semiring) -> Semiring:
    return Semiring(s.name, s.add, lambda x, y: s.times(y, x), s.sql_add, s.sql_times, s.again)


def heavy_inner(a: SparseMatrix, b: SparseMatrix, parts: int) -> list[int]:
    """Inner indices whose products alone are more than a part's share of all, of which there are fewer
    than parts."""
    one = a.df.groupBy(F.col("j").alias("k")).agg(F.count(F.lit(1)).alias("na"))
    two = b.df.groupBy(F.col("i").alias("k")).agg(F.count(F.lit(1)).alias("nb"))
    work = materialize(one.join(two, "k").select("k", (F.col("na") * F.col("nb")).alias("w")), "inner-work")
    total = work.agg(F.sum("w")).first()[0] or 0
    return sorted(r["k"] for r in work.where(F.col("w") * parts > total).select("k").collect())


def cell_points(a: SparseMatrix, b: SparseMatrix, grid: Grid, threads: int | None = None, block: int | None = None, transpose_b: bool = True, hubs: list[int] | None = None) -> DataFrame:
    """The work cube dealt to the grid: rows (cell, i, k, j, a, b), the join done inside the cells.
    A's entries go to the pc cells of their grid row and layer, B's to the pr cells of their column.
    A cell's sub-splits share its inner indices; a hub's products are shared by A's rows instead,
    and B's entries of it go to all sub-splits."""
    spark = configure(a.df.sparkSession)
    left, right = _sides(a, b)
    t = threads or threads_per_cell(spark, grid)
    k, n = F.col("k"), F.lit(t).cast("bigint")
    part_a = part_b = F.pmod(k, n)
    if hubs and t > 1:
        part_a = F.when(k.isin(hubs), F.pmod(F.xxhash64("i"), n)).otherwise(part_a)
        right = right.withColumn("part", F.explode(F.when(k.isin(hubs), F.sequence(F.lit(0).cast("bigint"), n - 1)).otherwise(F.array(part_b))))
        part_b = F.col("part")
    left = fan_out(left, grid.pc, "gj")
    left = to_cells(left, row_block(F.col("i"), a.nrows, grid), F.col("gj"), layer_of(k, a.ncols, grid), part_a, grid, t).drop("gj")
    right = fan_out(right, grid.pr, "gi")
    right = to_cells(right, F.col("gi"), col_block(F.col("j"), b.ncols, grid), layer_of(k, a.ncols, grid), part_b, grid, t).drop("gi", "part")
    keys = ["cell", "k"]
    if block is not None:
        left, right = (x.withColumn("panel", panel_of(k, a.ncols, grid, block)) for x in (left, right))
        keys.append("panel")
    if transpose_b:  # clustered by inner index inside the cell, so that a row of B is read in one run
        right = right.sortWithinPartitions("cell", "k")
    return left.join(right, keys)


def layer_results(a: SparseMatrix, b: SparseMatrix, grid: Grid, semiring: Semiring = PLUS_TIMES, block: int | None = None, transpose_b: bool = False) -> DataFrame:
    """Each cell's own result before the exchange across layers: (cell, i, j, v), one row per entry
    and cell (and sub-split, of which a cell here has one)."""
    return _combined(cell_points(a, b, grid, 1, block, transpose_b), semiring, ("cell", "i", "j"))


def grid3d(a: SparseMatrix, b: SparseMatrix, grid: Grid, semiring: Semiring = PLUS_TIMES, block: int | None = None, kernel: str = "sql", transpose_b: bool = False, layout: str = "split",
           threads: int | None = None, hubs: list[int] | None = None) -> SparseMatrix:
    """Layered plan: both operands to their cells, products combined inside each cell, partial
    results exchanged by output entry and merged. With one layer a cell owns its results: they are
    combined where they are made, on a grid cut fine enough for all workers. kernel: sql, heap or acc.
    layout replicate stores every input entry on all layers, and each layer reads its own copy, for
    comparison. threads: sub-splits of a cell; hubs: inner indices to be shared by sub-splits."""
    if kernel != "sql":
        from layermul.operators.kernels import cell_kernel

        partial = cell_kernel(a, b, grid, kernel, semiring)
        return SparseMatrix(partial.groupBy("i", "j").agg(semiring.merge(F.col("v")).alias("v")), a.nrows, b.ncols)
    if layout == "replicate":
        a = _replicated(a, grid, "j", a.ncols)
        b = _replicated(b, grid, "i", a.ncols)
    if grid.pl == 1:
        n = int(a.df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        points = cell_points(a, b, refined(grid, max(n, grid.cells * (threads or 1))), 1, block, transpose_b)
        return SparseMatrix(_combined(points, semiring, ("cell", "i", "j")).select("i", "j", "v"), a.nrows, b.ncols)
    points = cell_points(a, b, grid, threads, block, transpose_b, hubs)
    # the partial pass of this aggregate combines inside the cell; its exchange is the one across layers
    return SparseMatrix(_combined(points, semiring), a.nrows, b.ncols)


def _replicated(m: SparseMatrix, grid: Grid, inner: str, size: int) -> SparseMatrix:
    """A copy of m written for every layer, read back by the layer that uses the entry."""
    copies = materialize(fan_out(m.df, grid.pl, "gl"), "replicated")
    return m.with_df(copies.where(F.col("gl") == layer_of(F.col(inner), size, grid)))


def local_sql(a: SparseMatrix, b: SparseMatrix, semiring: Semiring = PLUS_TIMES, most: int = 4_000_000, beyond: str = "refuse") -> SparseMatrix:
    """The shared-memory routine for comparison: both operands to one task, which joins and aggregates.
    Operands of more than `most` entries together are refused, or with beyond rows cut into runs of A's rows,
    a task each with the rows of B that they use."""
    n = a.nnz() + b.nnz()
    if n > most and beyond == "rows":
        return oned(a, b, semiring, parts=-(-n // most), rowmap="block")
    if n > most:
        raise TooMuchWork(f"{n} entries in one task, {most} allowed")
    spark = configure(a.df.sparkSession)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    left, right = (x.withColumn("w", F.pmod(F.xxhash64("k"), F.lit(1)).cast("int")).repartition(parts, "w") for x in _sides(a, b))
    return SparseMatrix(_combined(left.join(right.hint("shuffle_hash"), ["w", "k"]), semiring, ("w", "i", "j")).select("i", "j", "v"), a.nrows, b.ncols)


def grid2d(a: SparseMatrix, b: SparseMatrix, pr: int, pc: int, semiring: Semiring = PLUS_TIMES, block: int | None = None, mode: str = "fused", merge: str = "end") -> SparseMatrix:
    """Two-dimensional plan. mode fused: all panels in one join. mode staged: one product per panel of
    the inner index, as many jobs as panels; merge stage combines after each, merge end holds all
    stage results and merges them once."""
    grid = Grid(pr, pc, 1)
    if mode == "fused":
        return grid3d(a, b, grid, semiring, block)
    left, right = _sides(a, b)
    panels = [r["p"] for r in left.select(panel_of(F.col("k"), a.ncols, grid, block).alias("p")).distinct().orderBy("p").collect()]  # stages, not data
    done: list[DataFrame] = []
    for p in panels:
        one, two = (x.where(panel_of(F.col("k"), a.ncols, grid, block) == p) for x in (left, right))
        part = _combined(cell_points(SparseMatrix(one.toDF("i", "j", "v"), a.nrows, a.ncols), SparseMatrix(two.toDF("i", "j", "v"), b.nrows, b.ncols), grid), semiring)
        if merge == "stage" and done:
            part = done.pop().unionByName(part).groupBy("i", "j").agg(semiring.merge(F.col("v")).alias("v"))
        done.append(materialize(part, f"stage{p}"))
    if not done:
        return SparseMatrix(_combined(left.join(right, "k"), semiring), a.nrows, b.ncols)
    lists = reduce(DataFrame.unionByName, done)
    return SparseMatrix(lists.groupBy("i", "j").agg(semiring.merge(F.col("v")).alias("v")) if len(done) > 1 else lists, a.nrows, b.ncols)


def fiber_moves(c_int: DataFrame, ncols: int, grid: Grid) -> DataFrame:
    """Rows of layer results with the layer that made them and the one that owns them."""
    return c_int.withColumn("owner", slice_of(F.col("j"), ncols, grid))


def multiply(a: SparseMatrix, b: SparseMatrix, semiring: Semiring = PLUS_TIMES, plan: str = "auto", grid: Grid | None = None, mask: SparseMatrix | None = None,
             complement: bool = False, drop_below=None, max_flops: int | None = None) -> SparseMatrix:
    """C = A B. plan: auto, catalyst, oned, oned_broadcast, grid2d or grid3d. mask keeps (or with
    complement leaves out) the entries of a pattern; A's rows and B's columns that the mask doesn't
    touch are left out before the product. drop_below leaves out small results. max_flops refuses
    products with more scalar products than that before any is made. Under auto, inner indices that
    outweigh a layer are shared by sub-splits of its cells."""
    from .planner import BROADCAST_ENTRIES, choose_plan, measure

    auto = plan == "auto"
    stats = measure(a, b) if auto or max_flops is not None else None
    if max_flops is not None and stats.flops > max_flops:
        raise TooMuchWork(f"{stats.flops} scalar products, {max_flops} allowed")
    if mask is not None and not complement:
        a = a.with_df(a.df.join(mask.df.select("i").distinct(), "i", "left_semi"))
        b = b.with_df(b.df.join(mask.df.select("j").distinct(), "j", "left_semi"))
    if auto:
        workers = int(a.df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        plan, grid = choose_plan(stats, workers)
    elif plan == "oned_broadcast" and b.nnz() > BROADCAST_ENTRIES:
        plan = "oned"
    if plan in ("grid2d", "grid3d"):
        grid = grid or Grid(2, 2, 2 if plan == "grid3d" else 1)
        hubs = threads = None
        if auto and grid.pl > 1 and stats.heaviest * grid.pl > stats.flops:  # more than a layer's share
            hubs = heavy_inner(a, b, grid.pl)
            threads = max(threads_per_cell(a.df.sparkSession, grid), 1 - (-stats.heaviest * grid.pl // stats.flops))
        c = grid3d(a, b, grid, semiring, threads=threads, hubs=hubs)
    elif plan in ("oned", "oned_broadcast", "oned_broadcast_a"):
        c = oned(a, b, semiring, "col" if plan == "oned_broadcast_a" else "row", broadcast=plan != "oned")
    elif plan == "catalyst":
        c = catalyst(a, b, semiring)
    else:
        raise ValueError(f"no plan {plan!r}")
    if mask is not None:
        c = c.mask(mask, complement)
    return c if drop_below is None else c.where(F.abs(F.col("v")) >= drop_below)
