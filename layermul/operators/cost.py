"""Measures of a product: work, words moved, memory growth, imbalance, storage."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from layermul.matrix import SparseMatrix
from layermul.plans.grid import Grid, col_block, fan_out, layer_of, owner_a, row_block, slice_of
from layermul.plans.multiply import catalyst


def _counts(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    one = a.df.groupBy(F.col("j").alias("k")).agg(F.count(F.lit(1)).alias("na"))
    two = b.df.groupBy(F.col("i").alias("k")).agg(F.count(F.lit(1)).alias("nb"))
    return one.join(two, "k")


def flops(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """One row: the number of scalar products."""
    return _counts(a, b).agg(F.coalesce(F.sum(F.col("na") * F.col("nb")), F.lit(0)).cast("bigint").alias("flops"))


def flops_by_column(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    one = a.df.groupBy(F.col("j").alias("k")).agg(F.count(F.lit(1)).alias("na"))
    return b.df.select(F.col("i").alias("k"), "j").join(one, "k").groupBy("j").agg(F.sum("na").alias("flops"), F.count(F.lit(1)).alias("width"))


def heap_cost(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """Products of each output column times the logarithm of the columns it merges, summed."""
    per = flops_by_column(a, b).join(b.df.groupBy("j").agg(F.count(F.lit(1)).alias("nb")), "j")
    return per.agg(F.round(F.sum(F.col("flops") * F.log2(F.col("nb").cast("double"))), 3).alias("cost"))


def merge_cost(lists: DataFrame) -> DataFrame:
    """Entries of all lists (list, ...) times the logarithm of their number."""
    return lists.agg(F.count(F.lit(1)).alias("n"), F.countDistinct("list").alias("k")).select(F.round(F.col("n") * F.log2(F.col("k").cast("double")), 3).alias("cost"))


def profile(m: SparseMatrix) -> DataFrame:
    """Entries, dimensions, nonempty rows and columns, and whether pattern and values are symmetric."""
    n = m.df.agg(F.count(F.lit(1)).alias("nnz"), F.countDistinct("i").alias("rows"), F.countDistinct("j").alias("cols"))
    odd = m.df.exceptAll(m.t.df).agg((F.count(F.lit(1)) == 0).alias("symmetric"))
    return n.join(odd).select(F.lit(m.nrows).cast("bigint").alias("nrows"), F.lit(m.ncols).cast("bigint").alias("ncols"), "nnz", "rows", "cols", "symmetric")


def work_by_cell(a: SparseMatrix, b: SparseMatrix, grid: Grid) -> DataFrame:
    """(gi, gj, gl, flops): scalar products of each cell, from counts per inner index and block."""
    k = F.col("k")
    one = a.df.select(row_block(F.col("i"), a.nrows, grid).alias("gi"), F.col("j").alias("k")).groupBy("gi", "k").agg(F.count(F.lit(1)).alias("na"))
    two = b.df.select(col_block(F.col("j"), b.ncols, grid).alias("gj"), F.col("i").alias("k")).groupBy("gj", "k").agg(F.count(F.lit(1)).alias("nb"))
    return one.join(two, "k").groupBy("gi", "gj", layer_of(k, a.ncols, grid).alias("gl")).agg(F.sum(F.col("na") * F.col("nb")).alias("flops"))


def assign_work(a: SparseMatrix, b: SparseMatrix, grid: Grid, kind: str) -> DataFrame:
    """(worker, points) of the work cube: slabs of rows (1d), bundles of lines along the inner index
    (2d) or boxes (3d), over as many workers as the grid has cells."""
    if kind == "1d":
        grid = Grid(grid.cells, 1, 1)
    elif kind == "2d":
        grid = Grid(grid.pr, grid.pc * grid.pl, 1)
    cells = work_by_cell(a, b, grid)
    return cells.select(((F.col("gi") * grid.pc + F.col("gj")) * grid.pl + F.col("gl")).cast("bigint").alias("worker"), F.col("flops").alias("points"))


def layer_pattern(a: SparseMatrix, b: SparseMatrix, grid: Grid) -> DataFrame:
    """(gl, i, j): the entries that each layer makes."""
    one = a.df.select("i", F.col("j").alias("k"))
    two = b.df.select(F.col("i").alias("k"), "j")
    return one.join(two, "k").select(layer_of(F.col("k"), a.ncols, grid).alias("gl"), "i", "j").distinct()


def memory_factor(a: SparseMatrix, b: SparseMatrix, grid: Grid) -> DataFrame:
    """Entries of all layers' results and of the product, and the products that bound both."""
    made = layer_pattern(a, b, grid)
    n = made.agg(F.count(F.lit(1)).alias("nnz_int"))
    c = made.select("i", "j").distinct().agg(F.count(F.lit(1)).alias("nnz_c"))
    return n.join(c).join(flops(a, b))


def imbalance(a: SparseMatrix, b: SparseMatrix, grid: Grid) -> DataFrame:
    """cells, flops, max_flops: mean is flops / cells over all cells, idle ones too."""
    work = work_by_cell(a, b, grid)
    return work.agg(F.lit(grid.cells).cast("bigint").alias("cells"), F.coalesce(F.sum("flops"), F.lit(0)).cast("bigint").alias("flops"), F.coalesce(F.max("flops"), F.lit(0)).cast("bigint").alias("max_flops"))


def words_moved(a: SparseMatrix, b: SparseMatrix, grid: Grid) -> DataFrame:
    """(phase, total, max_cell): entries that change owner when B is dealt to its layers, panels are
    broadcast along rows and columns, and partial results go to their owners. A cell counts what it
    receives."""
    inner = a.ncols
    gi, gj, gl = owner_a(F.col("i"), F.col("j"), a.nrows, inner, grid)
    own_a = a.df.select(gi.alias("gi"), gj.alias("own"), gl.alias("gl"))
    a_cast = fan_out(own_a, grid.pc, "gj").where("gj <> own").groupBy("gi", "gj", "gl").count()
    row, col, held = owner_a(F.col("i"), F.col("j"), b.nrows, b.ncols, grid)
    own_b = b.df.select(row.alias("own"), col.alias("gj"), held.alias("held"), layer_of(F.col("i"), inner, grid).alias("gl"))
    deal = own_b.where("held <> gl").groupBy(F.col("own").alias("gi"), "gj", "gl").count()
    b_cast = fan_out(own_b.select("own", "gj", "gl"), grid.pr, "gi").where("gi <> own").groupBy("gi", "gj", "gl").count()
    made = layer_pattern(a, b, grid)
    c_move = made.select(row_block(F.col("i"), a.nrows, grid).alias("gi"), col_block(F.col("j"), b.ncols, grid).alias("gj"), "gl", slice_of(F.col("j"), b.ncols, grid).alias("to")).where("gl <> to").groupBy("gi", "gj", "to").count()
    out = None
    for phase, cells in (("b_deal", deal), ("a_broadcast", a_cast), ("b_broadcast", b_cast), ("c_exchange", c_move)):
        one = cells.agg(F.lit(phase).alias("phase"), F.coalesce(F.sum("count"), F.lit(0)).cast("bigint").alias("total"), F.coalesce(F.max("count"), F.lit(0)).cast("bigint").alias("max_cell"))
        out = one if out is None else out.unionByName(one)
    return out


def storage_words(m: SparseMatrix, grid: Grid) -> DataFrame:
    """(format, words) over all cells: triples; column pointers for every column of every cell, or for
    the nonempty ones only, beside index and value; and the last with inputs kept on all layers."""
    gi, gj, gl = owner_a(F.col("i"), F.col("j"), m.nrows, m.ncols, grid)
    cells = m.df.select(gi.alias("gi"), gj.alias("gj"), gl.alias("gl"), "j")
    n = cells.agg(F.count(F.lit(1)).alias("nnz"), F.countDistinct("gi", "gj", "gl", "j").alias("full"))
    all_columns = m.ncols * grid.pr + grid.cells
    return n.selectExpr(
        f"stack(4, 'triples', 3 * nnz, 'columns', 2 * nnz + {all_columns}, 'nonempty_columns', 2 * nnz + 2 * full, 'replicated', {grid.pl} * (2 * nnz + 2 * full)) AS (format, words)"
    )


def nnz_by_cell(m: SparseMatrix, grid: Grid, kind: str = "rollup") -> DataFrame:
    """Entries by grid row, column and layer with subtotals: rollup, cube or plain."""
    gi, gj, gl = owner_a(F.col("i"), F.col("j"), m.nrows, m.ncols, grid)
    cells = m.df.select(gi.alias("gi"), gj.alias("gj"), gl.alias("gl"))
    return getattr(cells, {"rollup": "rollup", "cube": "cube", "plain": "groupBy"}[kind])("gi", "gj", "gl").agg(F.count(F.lit(1)).alias("nnz"))


def product_report(named: dict[str, tuple[SparseMatrix, SparseMatrix | None]]) -> DataFrame:
    """(matrix, what, nnz): sizes of A and A A, and of R, RᵀA and RᵀA R where R is given."""
    out = None
    for name, (a, r) in named.items():
        parts = {"A": a, "AA": catalyst(a, a)}
        if r is not None:
            rta = catalyst(r.t, a)
            parts |= {"R": r, "RtA": rta, "RtAR": catalyst(rta, r)}
        for what, m in parts.items():
            one = m.df.agg(F.lit(name).alias("matrix"), F.lit(what).alias("what"), F.count(F.lit(1)).alias("nnz"))
            out = one if out is None else out.unionByName(one)
    return out
