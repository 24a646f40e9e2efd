"""Named queries over the given tables, each with its DuckDB twin where SQL can say it.

A query is a function of (spark, sf_dir); oracle_sql() has the same names. Small products return their
entries, large ones a checksum for each row.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from layermul.functions.sqlapi import product_sql, register, sql_multiply
from layermul.functions.udfs import user_semiring
from layermul.matrix import AffinePermutation, SparseMatrix, digest_permutation, permute_by
from layermul.operators import coarsen, cost, folded, graph, kernels, layout, merge, vector
from layermul.plans.grid import Grid, owner_a, owner_bhat
from layermul.plans.multiply import catalyst, grid2d, grid3d, heavy_inner, local_sql, multiply, oned
from layermul.plans.planner import estimate_nnz_c, measure, model_sweep
from layermul.semiring import MAX_MIN, MIN_FIRST, MIN_PLUS, MIN_SECOND, OR_AND, PLUS_PAIR, PLUS_TIMES, SEMIRINGS, Semiring
from layermul.session import configure, fresh_path
from layermul.sources import datasets, io
from layermul.sources.datasets import SQL, table
from layermul.sources.generators import CLASSES, rmat, rmat_sql

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, tuple[Query, str | None]] = {}
_N_PART = "(SELECT max(p_partkey) + 1 FROM part)"


def _add(name: str, query: Query, sql: str | None) -> None:
    _QUERIES[name] = (query, sql)


def _t(sql: str) -> str:
    return f"SELECT j AS i, i AS j, v FROM ({sql})"


def _product(a: str, b: str, s: Semiring = PLUS_TIMES) -> str:
    term = s.sql_times.format(a="a.v", b="b.v")
    return f"SELECT a.i, b.j, {s.sql_add.format(x=term)} AS v FROM ({a}) a JOIN ({b}) b ON a.j = b.i GROUP BY a.i, b.j"


def checksum(m: SparseMatrix) -> DataFrame:
    """(i, cnt, total, mix) of each row: what a large product is compared by."""
    return m.df.groupBy("i").agg(F.count(F.lit(1)).alias("cnt"), F.sum("v").cast("bigint").alias("total"), F.sum(F.col("v") * F.pmod(F.col("j"), F.lit(97))).cast("bigint").alias("mix"))


def _checksum(sql: str) -> str:
    return f"SELECT i, COUNT(*) AS cnt, CAST(SUM(v) AS BIGINT) AS total, CAST(SUM(v * (j % 97)) AS BIGINT) AS mix FROM ({sql}) GROUP BY i"


_X1, _X4, _X5, _X6, _X8 = (SQL[n] for n in ("order_part", "next_part", "next_part_sym", "mesh_part", "nation_trade"))
_X1tX1 = _product(_t(_X1), _X1)
_X6X6 = _product(_X6, _X6)
_X4X6 = _product(_X4, _X6)
_R10 = rmat_sql("skewed", 10)


def _x1(s, d):
    return datasets.order_part(s, d)


def _x4(s, d):
    return datasets.next_part(s, d)


def _x5(s, d):
    return datasets.next_part_sym(s, d)


def _mesh(s, d):
    return datasets.mesh_part(s, d)


def _pair(s, d, cls: str) -> list[SparseMatrix]:
    """The two matrices of _PAIRS; where an operand names no index as large as the other does, it has none of it."""
    a, b = (getattr(datasets, n)(s, d) for n in _PAIRS[cls])
    inner = max(a.ncols, b.nrows)
    return [SparseMatrix(a.df, a.nrows, inner), SparseMatrix(b.df, inner, b.ncols)]


# --- products: plans, variants and baselines -------------------------------------------------------

for _n in ("part_supp", "cust_part", "user_hour", "nation_trade", "host_link", "vec_sim", "conv_role", "next_part", "next_part_sym", "order_part", "mesh_part", "json_matrix"):
    _add(f"matrix_{_n}", lambda s, d, n=_n: checksum(datasets.BUILDERS[n](s, d)), _checksum(SQL[_n]))
_add("matrix_doc_token_whole", lambda s, d: checksum(datasets.doc_token(s, d)), _checksum(SQL["doc_token"]))
_add("mm_doc_token_whole", lambda s, d: folded.folded_lists(*datasets.doc_words(s, d)), _checksum(_product(SQL["doc_token"], _t(SQL["doc_token"]))))

_add("mm_catalyst_order_part", lambda s, d: catalyst(_x1(s, d).t, _x1(s, d)).df, _X1tX1)
_add("mm_grid3d_order_part", lambda s, d: grid3d(_x1(s, d).t, _x1(s, d), Grid(2, 2, 2)).df, _X1tX1)
_add("mm_auto_order_part", lambda s, d: multiply(_x1(s, d).t, _x1(s, d)).df, _X1tX1)
for _by in ("row", "col", "inner"):
    _add(f"mm_oned_{_by}", lambda s, d, by=_by: oned(_mesh(s, d), _mesh(s, d), by=by, parts=8).df, _X6X6)
_add("mm_oned_block", lambda s, d: oned(_mesh(s, d), _mesh(s, d), parts=8, rowmap="block").df, _X6X6)
_add("mm_oned_bcast", lambda s, d: multiply(_mesh(s, d), _mesh(s, d), plan="oned_broadcast").df, _X6X6)
_add("mm_grid2d_mesh", lambda s, d: grid2d(_mesh(s, d), _mesh(s, d), 2, 2).df, _X6X6)
_CUSTtCUST = _product(_t(SQL["cust_part"]), SQL["cust_part"])
_add("mm_grid2d_rect_whole", lambda s, d: (lambda m: checksum(grid2d(m.t, m, 2, 3)))(datasets.cust_part(s, d)), _checksum(_CUSTtCUST))
for _b in (1, 7, None):
    _add(f"mm_grid2d_blocked_{_b or 'all'}", lambda s, d, b=_b: grid2d(_mesh(s, d), _mesh(s, d), 2, 2, block=b).df, _X6X6)
for _m in ("stage", "end"):
    _add(f"mm_grid2d_staged_{_m}", lambda s, d, m=_m: grid2d(_mesh(s, d), _mesh(s, d), 2, 2, mode="staged", merge=m).df, _X6X6)
_add("mm_grid3d_mesh", lambda s, d: grid3d(_mesh(s, d), _mesh(s, d), Grid(2, 2, 2), transpose_b=True).df, _X6X6)
_add("mm_grid3d_uneven", lambda s, d: grid3d(_mesh(s, d), _mesh(s, d), Grid(3, 2, 5)).df, _X6X6)
_add("mm_grid3d_one_layer", lambda s, d: grid3d(_mesh(s, d), _mesh(s, d), Grid(4, 4, 1)).df, _X6X6)
_add("mm_grid3d_all_layers", lambda s, d: grid3d(_mesh(s, d), _mesh(s, d), Grid(1, 1, 16)).df, _X6X6)
_add("mm_replicated", lambda s, d: grid3d(_mesh(s, d), _mesh(s, d), Grid(2, 2, 2), layout="replicate").df, _X6X6)
_add("mm_grid3d_next_part", lambda s, d: checksum(grid3d(_x4(s, d), _x4(s, d), Grid(2, 2, 2))), _checksum(_product(_X4, _X4)))
_add("mm_grid3d_trade", lambda s, d: grid3d(datasets.nation_trade(s, d), datasets.nation_trade(s, d), Grid(2, 2, 2)).df, _product(_X8, _X8))
#: Pairs from the given tables in place of random ones: neighbours in a band, few heavy inner indices, parts
#: that follow each other anywhere.
_PAIRS = {"community": ("mesh_part", "next_part"), "skewed": ("user_type", "type_hour"), "uniform": ("next_part", "mesh_part")}
for _c in CLASSES:
    _add(f"rmat_{_c}", lambda s, d, c=_c: rmat(s, c, 10).df, rmat_sql(_c, 10))
    if _c == "community":
        _add("mm_grid3d_rmat_community", lambda s, d: checksum(grid3d(_mesh(s, d), _mesh(s, d), Grid(2, 2, 4))), _checksum(_X6X6))
    else:
        _add(f"mm_grid3d_rmat_{_c}", lambda s, d, c=_c: checksum(grid3d(rmat(s, c, 10), rmat(s, c, 10), Grid(2, 2, 4))), _checksum(_product(rmat_sql(_c, 10), rmat_sql(_c, 10))))
    _add(f"mm_grid3d_pair_{_c}", lambda s, d, c=_c: checksum(grid3d(*_pair(s, d, c), Grid(2, 2, 2))), _checksum(_product(*(SQL[n] for n in _PAIRS[_c]))))
for _s in (MIN_PLUS, MAX_MIN, MIN_SECOND, MIN_FIRST, PLUS_PAIR, *(SEMIRINGS[n] for n in ("max_second", "any_pair", "plus_second", "max_times"))):
    _add(f"semiring_{_s.name}", lambda s, d, r=_s: multiply(_mesh(s, d), _mesh(s, d), r, "grid3d", Grid(2, 2, 2)).df, _product(_X6, _X6, _s))
_add("semiring_or_and", lambda s, d: (lambda m: grid3d(m, m, Grid(2, 2, 2), OR_AND).df)(_mesh(s, d).apply(lambda v: v > 0)), _product(*[f"SELECT i, j, v > 0 AS v FROM ({_X6})"] * 2, OR_AND))

# --- kernels, layouts and merges -------------------------------------------------------------------

_add("kernel_heap", lambda s, d: kernels.heap_kernel(_mesh(s, d), _mesh(s, d), Grid(2, 2, 2)).df, _X6X6)
_add("kernel_heap_parts", lambda s, d: kernels.heap_kernel(_mesh(s, d), _mesh(s, d), Grid(2, 2, 1), parts=3).df, _X6X6)
_add("kernel_dense_acc", lambda s, d: kernels.dense_acc_kernel(_mesh(s, d), _mesh(s, d), Grid(2, 2, 2)).df, _X6X6)
_add("kernel_heap_min_plus", lambda s, d: kernels.heap_kernel(_mesh(s, d), _mesh(s, d), Grid(2, 2, 2), MIN_PLUS).df, _product(_X6, _X6, MIN_PLUS))
_add("kernel_grid3d_heap", lambda s, d: grid3d(_mesh(s, d), _mesh(s, d), Grid(2, 2, 2), kernel="heap").df, _X6X6)
_add("kernel_column_sql", lambda s, d: kernels.column_kernel_sql(_mesh(s, d), _mesh(s, d)).df, _X6X6)
_add("kernel_sorted", lambda s, d: kernels.out_of_order(kernels.sorted_triples(kernels.heap_kernel(_mesh(s, d), _mesh(s, d), Grid(2, 2, 1)))), "SELECT CAST(0 AS BIGINT) AS violations")
_add("kway_merge", lambda s, d: merge.kway_merge(merge.stage_lists(_mesh(s, d), _mesh(s, d), 4)), _X6X6)
_add("kway_merge_heap", lambda s, d: merge.kway_merge_heap(merge.stage_lists(_mesh(s, d), _mesh(s, d), 4)), _X6X6)
_add("kway_merge_16", lambda s, d: checksum(SparseMatrix(merge.kway_merge(merge.stage_lists(_x4(s, d), _mesh(s, d), 16)), 0, 0)), _checksum(_X4X6))
_add("merge_then_reduce", lambda s, d: merge.merge_then_reduce(merge.stage_lists(_mesh(s, d), _mesh(s, d), 4)), _X6X6)
_add("merge_equal_work", lambda s, d: merge.equal_work_cuts(_x1(s, d), 16), f"""SELECT part, min(j) AS lo, max(j) AS hi, CAST(sum(n) AS BIGINT) AS nnz FROM (SELECT j, n, CAST(coalesce(sum(n) OVER (ORDER BY j ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) * 16 // sum(n) OVER () AS BIGINT) AS part
    FROM (SELECT j, count(*) AS n FROM ({_X1}) GROUP BY j)) GROUP BY part""")  # fmt: skip
_add("dcsc", lambda s, d: layout.to_dcsc(_x1(s, d)).df.select("j", F.size("entries").cast("bigint").alias("n"), F.col("entries")[0]["i"].alias("first_i"), F.element_at("entries", -1)["i"].alias("last_i")), f"SELECT j, COUNT(*) AS n, MIN(i) AS first_i, MAX(i) AS last_i FROM ({_X1}) GROUP BY j")
_add("dcsc_roundtrip", lambda s, d: layout.to_dcsc(_x1(s, d), longest=1000).matrix().df, _X1)
_add("dcsc_columns", lambda s, d: layout.to_dcsc(_x1(s, d)).columns(100, 200).matrix().df, f"SELECT * FROM ({_X1}) WHERE j >= 100 AND j < 200")
_add("every_column", lambda s, d: layout.every_column(_x4(s, d)).select("j", F.size("entries").cast("bigint").alias("n")), f"SELECT k AS j, COALESCE(n, 0) AS n FROM (SELECT unnest(range({_N_PART})) AS k) LEFT JOIN (SELECT j, COUNT(*) AS n FROM ({_X4}) GROUP BY j) ON j = k")
_add("aux_index", lambda s, d: layout.aux_index(layout.to_dcsc(_x1(s, d)), 64), f"SELECT j // 64 AS chunk, COUNT(DISTINCT j) AS n, MIN(j) AS lo, MAX(j) AS hi FROM ({_X1}) GROUP BY 1")

_Q6 = f"SELECT i, j, v * 0.25::DOUBLE AS v FROM ({_X6})"  # quarters: sums are exact in any order
_Q6Q6 = f"SELECT a.i, b.j, SUM(a.v * b.v) AS v FROM ({_Q6}) a JOIN ({_Q6}) b ON a.j = b.i GROUP BY a.i, b.j"


def _quarters(s, d) -> SparseMatrix:
    return _mesh(s, d).apply(lambda v: v * F.lit(0.25))


_add("kernel_heap_double", lambda s, d: (lambda m: kernels.heap_kernel(m, m, Grid(2, 2, 2)).df)(_quarters(s, d)), _Q6Q6)
_add("kernel_dense_acc_double", lambda s, d: (lambda m: kernels.dense_acc_kernel(m, m, Grid(2, 2, 2)).df)(_quarters(s, d)), _Q6Q6)
_add("kernel_column_sql_double", lambda s, d: (lambda m: kernels.column_kernel_sql(m, m).df)(_quarters(s, d)), _Q6Q6)
_add("kway_merge_heap_double", lambda s, d: (lambda m: merge.kway_merge_heap(merge.stage_lists(m, m, 4)))(_quarters(s, d)), _Q6Q6)
_add("mm_local_sql", lambda s, d: local_sql(_mesh(s, d), _mesh(s, d), beyond="rows").df, _X6X6)
_add("mm_grid3d_hubs", lambda s, d: (lambda a, b: checksum(grid3d(a, b, Grid(1, 1, 2), threads=8, hubs=heavy_inner(a, b, 64))))(*_pair(s, d, "skewed")), _checksum(_product(SQL["user_type"], SQL["type_hour"])))
for _w in (4, 16):
    _add(f"kway_merge_cell_{_w}x{_w}", lambda s, d, w=_w: checksum(SparseMatrix(merge.kway_merge(merge.cell_stage_lists(_x4(s, d), _mesh(s, d), Grid(w, w, 1))), 0, 0)),
         _checksum(f"SELECT * FROM ({_X4X6}) WHERE i < ({_N_PART} + {_w - 1}) // {_w} AND j < ({_N_PART} + {_w - 1}) // {_w}"))

# --- measures --------------------------------------------------------------------------------------

_FLOPS = "SELECT CAST(COALESCE(SUM(na * nb), 0) AS BIGINT) AS flops FROM (SELECT j AS k, COUNT(*) AS na FROM ({a}) GROUP BY 1) JOIN (SELECT i AS k, COUNT(*) AS nb FROM ({b}) GROUP BY 1) USING (k)"


def _ceil(n: str, d: int) -> str:
    return f"(({n} + {d - 1}) // {d})"


def _layer(k: str, n: str, g: Grid) -> str:
    return f"(({k} % {_ceil(n, g.pc)}) // {_ceil(_ceil(n, g.pc), g.pl)})"


def _owner(n: str, g: Grid, i: str = "i", j: str = "j") -> tuple[str, str, str]:
    return f"({i} // {_ceil(n, g.pr)})", f"({j} // {_ceil(n, g.pc)})", _layer(j, n, g)


def _made(a: str, n: str, g: Grid) -> str:
    return f"SELECT DISTINCT {_layer('a.j', n, g)} AS gl, a.i, b.j FROM ({a}) a JOIN ({a}) b ON a.j = b.i"


def _words_sql(a: str, n: str, g: Grid) -> str:
    """The square product's words, phase by phase."""
    gi, gj, gl = _owner(n, g)
    pc, pr = g.pc, g.pr
    phases = {
        "b_deal": f"SELECT {gi} AS gi, {gj} AS gj, {_layer('i', n, g)} AS gl FROM ({a}) WHERE {gl} <> {_layer('i', n, g)}",
        "a_broadcast": f"SELECT {gi} AS gi, c AS gj, {gl} AS gl FROM ({a}), range({pc}) r(c) WHERE c <> {gj}",
        "b_broadcast": f"SELECT c AS gi, {gj} AS gj, {_layer('i', n, g)} AS gl FROM ({a}), range({pr}) r(c) WHERE c <> {gi}",
        "c_exchange": f"SELECT {gi} AS gi, {gj} AS gj, {_layer('j', n, g)} AS gl FROM ({_made(a, n, g)}) m WHERE gl <> {_layer('j', n, g)}",
    }
    return " UNION ALL ".join(f"SELECT '{p}' AS phase, CAST(COALESCE(SUM(n), 0) AS BIGINT) AS total, CAST(COALESCE(MAX(n), 0) AS BIGINT) AS max_cell FROM (SELECT COUNT(*) AS n FROM ({q}) GROUP BY gi, gj, gl)" for p, q in phases.items())


def _work_sql(a: str, n: str, g: Grid) -> str:
    return f"""SELECT gi, gj, gl, CAST(SUM(na * nb) AS BIGINT) AS flops FROM (SELECT i // {_ceil(n, g.pr)} AS gi, j AS k, COUNT(*) AS na FROM ({a}) GROUP BY 1, 2)
        JOIN (SELECT j // {_ceil(n, g.pc)} AS gj, i AS k, {_layer('i', n, g)} AS gl, COUNT(*) AS nb FROM ({a}) GROUP BY 1, 2, 3) USING (k) GROUP BY 1, 2, 3"""


_add("flops", lambda s, d: cost.flops(_x4(s, d), _x4(s, d)), _FLOPS.format(a=_X4, b=_X4))
_add("flops_by_column", lambda s, d: cost.flops_by_column(_x4(s, d), _x4(s, d)), f"SELECT b.j, CAST(SUM(na) AS BIGINT) AS flops, COUNT(*) AS width FROM ({_X4}) b JOIN (SELECT j AS k, COUNT(*) AS na FROM ({_X4}) GROUP BY 1) ON k = b.i GROUP BY b.j")
_add("heap_cost", lambda s, d: cost.heap_cost(_mesh(s, d), _mesh(s, d)), f"""SELECT ROUND(SUM(flops * log2(nb)), 3) AS cost FROM (SELECT b.j, SUM(na)::DOUBLE AS flops FROM ({_X6}) b JOIN (SELECT j AS k, COUNT(*) AS na FROM ({_X6}) GROUP BY 1) ON k = b.i GROUP BY b.j)
    JOIN (SELECT j, COUNT(*) AS nb FROM ({_X6}) GROUP BY j) USING (j)""")  # fmt: skip
_add("merge_cost", lambda s, d: cost.merge_cost(merge.stage_lists(_mesh(s, d), _mesh(s, d), 4)), f"SELECT ROUND(COUNT(*) * log2(COUNT(DISTINCT l)), 3) AS cost FROM (SELECT DISTINCT a.j // {_ceil(_N_PART, 4)} AS l, a.i, b.j FROM ({_X6}) a JOIN ({_X6}) b ON a.j = b.i)")
for _name, _grid in {"mesh_221": Grid(4, 4, 1), "mesh_224": Grid(2, 2, 4)}.items():
    _add(f"words_moved_{_name}", lambda s, d, g=_grid: cost.words_moved(_mesh(s, d), _mesh(s, d), g), _words_sql(_X6, _N_PART, _grid))
    _add(f"imbalance_{_name}", lambda s, d, g=_grid: cost.imbalance(_mesh(s, d), _mesh(s, d), g), f"SELECT CAST({_grid.cells} AS BIGINT) AS cells, CAST(SUM(flops) AS BIGINT) AS flops, MAX(flops) AS max_flops FROM ({_work_sql(_X6, _N_PART, _grid)})")
for _name, _grid in {"2d": Grid(4, 4, 1), "c4": Grid(2, 2, 4), "c16": Grid(1, 1, 16)}.items():
    _add(f"words_moved_skewed_{_name}", lambda s, d, g=_grid: (lambda m: cost.words_moved(m, m, g))(rmat(s, "skewed", 10)), _words_sql(_R10, "1024", _grid))
    _add(f"memory_factor_{_name}", lambda s, d, g=_grid: (lambda m: cost.memory_factor(m, m, g))(_mesh(s, d)),
         f"SELECT * FROM (SELECT COUNT(*) AS nnz_int FROM ({_made(_X6, _N_PART, _grid)})), (SELECT COUNT(*) AS nnz_c FROM (SELECT DISTINCT i, j FROM ({_made(_X6, _N_PART, _grid)}))), ({_FLOPS.format(a=_X6, b=_X6)})")
for _kind, _grid in {"1d": Grid(16, 1, 1), "2d": Grid(4, 4, 1), "3d": Grid(2, 2, 4)}.items():
    _given = Grid(2, 2, 4) if _kind != "2d" else Grid(4, 1, 4)
    _add(f"assign_work_{_kind}", lambda s, d, k=_kind, g=_given: cost.assign_work(_mesh(s, d), _mesh(s, d), g, k), f"SELECT CAST((gi * {_grid.pc} + gj) * {_grid.pl} + gl AS BIGINT) AS worker, flops AS points FROM ({_work_sql(_X6, _N_PART, _grid)})")
_add("owner_blocks", lambda s, d: (lambda m: m.df.select(*[c.alias(n) for c, n in zip((*owner_a(F.col("i"), F.col("j"), m.nrows, m.ncols, Grid(3, 2, 5)), *owner_bhat(F.col("i"), F.col("j"), m.nrows, m.ncols, Grid(3, 2, 5))), ("ai", "aj", "al", "bi", "bj", "bl"), strict=True)]).groupBy("ai", "aj", "al", "bi", "bj", "bl").agg(F.count(F.lit(1)).alias("n")))(_mesh(s, d)),
     f"SELECT {', '.join(f'{x} AS {y}' for x, y in zip((*_owner(_N_PART, Grid(3, 2, 5)), *_owner(_N_PART, Grid(3, 2, 5))[:2], _layer('i', _N_PART, Grid(3, 2, 5))), ('ai', 'aj', 'al', 'bi', 'bj', 'bl'), strict=True))}, COUNT(*) AS n FROM ({_X6}) GROUP BY ALL")
_PERM = "((1237 * {0} + 11) % {1})"
_X6P = f"SELECT {_PERM.format('i', _N_PART)} AS i, {_PERM.format('j', _N_PART)} AS j, v FROM ({_X6})"


def _permuted(s, d):
    m = _mesh(s, d)
    return m.permute(AffinePermutation.near(m.nrows))


_add("permute", lambda s, d: _permuted(s, d).df, _X6P)
_add("permute_product", lambda s, d: (lambda m: multiply(m, m, plan="grid3d").unpermute(AffinePermutation.near(m.nrows)).df)(_permuted(s, d)), _X6X6)
_add("imbalance_permuted", lambda s, d: cost.imbalance(_permuted(s, d), _permuted(s, d), Grid(4, 4, 1)), f"SELECT CAST(16 AS BIGINT) AS cells, CAST(SUM(flops) AS BIGINT) AS flops, MAX(flops) AS max_flops FROM ({_work_sql(_X6P, _N_PART, Grid(4, 4, 1))})")
_XD = f"(WITH k AS MATERIALIZED (SELECT x, row_number() OVER (ORDER BY md5('42:' || x), x) - 1 AS p FROM (SELECT unnest(range({_N_PART})) AS x)) SELECT r.p AS i, c.p AS j, v FROM ({_X6}) JOIN k r ON i = r.x JOIN k c ON j = c.x)"
_digested = lambda s, d: (lambda m: permute_by(m, digest_permutation(s, m.nrows)))(_mesh(s, d))
_add("permute_digest", lambda s, d: _digested(s, d).df, f"SELECT * FROM {_XD}")
_add("imbalance_digest", lambda s, d: (lambda m: cost.imbalance(m, m, Grid(4, 4, 1)))(_digested(s, d)), f"SELECT CAST(16 AS BIGINT) AS cells, CAST(SUM(flops) AS BIGINT) AS flops, MAX(flops) AS max_flops FROM ({_work_sql(f'SELECT * FROM {_XD}', _N_PART, Grid(4, 4, 1))})")
_add("profile", lambda s, d: cost.profile(_mesh(s, d)), f"SELECT {_N_PART} AS nrows, {_N_PART} AS ncols, COUNT(*) AS nnz, COUNT(DISTINCT i) AS rows, COUNT(DISTINCT j) AS cols, TRUE AS symmetric FROM ({_X6})")
_add("profile_unsymmetric", lambda s, d: cost.profile(_x4(s, d)), f"SELECT {_N_PART} AS nrows, {_N_PART} AS ncols, COUNT(*) AS nnz, COUNT(DISTINCT i) AS rows, COUNT(DISTINCT j) AS cols, FALSE AS symmetric FROM ({_X4})")
_G = Grid(2, 2, 4)
_CELLCOLS = f"SELECT COUNT(*) AS nnz, COUNT(DISTINCT ({_owner(_N_PART, _G)[0]} || ':' || j)) AS c FROM ({_X6})"
_add("storage_words", lambda s, d: cost.storage_words(_mesh(s, d), _G), f"SELECT unnest(['triples', 'columns', 'nonempty_columns', 'replicated']) AS format, unnest([3 * nnz, 2 * nnz + {_N_PART} * {_G.pr} + {_G.cells}, 2 * nnz + 2 * c, {_G.pl} * (2 * nnz + 2 * c)]) AS words FROM ({_CELLCOLS})")
_PCB = ([16, 64, 256], [1, 4, 16], [64, 1024])
_MODEL = f"""SELECT CAST(p AS BIGINT) AS p, CAST(c AS BIGINT) AS c, CAST(b AS BIGINT) AS b, ROUND(n / (b * c) * log2(p / c) + c, 6) AS messages, ROUND((za + zb) / sqrt(p * c) + f / p, 6) AS words,
    ROUND((CASE WHEN c > 1 THEN (c - 1) + zb / p * (c - 1) / c ELSE 0 END) + st * (CASE WHEN q > 1 THEN (log2(q) + za / p * q / st * (q - 1) / q) + (log2(q) + zb / p * q / st * (q - 1) / q) ELSE 0 END)
      + (CASE WHEN c > 1 THEN (c - 1) + f / p * (c - 1) / c ELSE 0 END), 6) AS modelled
    FROM (SELECT p, c, b, sqrt(p / c) AS q, greatest(1.0, n / (b * c)) AS st, n, za, zb, f FROM (SELECT CAST(p AS DOUBLE) AS p, CAST(c AS DOUBLE) AS c, CAST(b AS DOUBLE) AS b, {_N_PART}::DOUBLE AS n, (SELECT COUNT(*) FROM ({_X6}))::DOUBLE AS za, (SELECT COUNT(*) FROM ({_X6}))::DOUBLE AS zb, ({_FLOPS.format(a=_X6, b=_X6)})::DOUBLE AS f
      FROM (VALUES (16), (64), (256)) x(p), (VALUES (1), (4), (16)) y(c), (VALUES (64), (1024)) z(b) WHERE c <= p))"""
_add("comm_model", lambda s, d: model_sweep(s, measure(_mesh(s, d), _mesh(s, d)), *_PCB), _MODEL)
_add("plan_measures", lambda s, d: (lambda m: s.createDataFrame([(m.nnz_a, m.nnz_b, m.flops)], "nnz_a bigint, nnz_b bigint, flops bigint"))(measure(_x4(s, d), _x4(s, d))), f"SELECT * FROM (SELECT COUNT(*) AS nnz_a, COUNT(*) AS nnz_b FROM ({_X4})), ({_FLOPS.format(a=_X4, b=_X4)})")
_add("estimate_nnz", lambda s, d: (lambda e, c: e.join(c).select("columns", (F.abs(F.col("estimate") - F.col("nnz")) <= 0.1 * F.col("nnz")).alias("near")))(estimate_nnz_c(_x4(s, d), _x4(s, d)).agg(F.count(F.lit(1)).alias("columns"), F.sum("estimate").alias("estimate")), catalyst(_x4(s, d), _x4(s, d)).df.agg(F.count(F.lit(1)).alias("nnz"))),
     f"SELECT COUNT(DISTINCT j) AS columns, TRUE AS near FROM ({_product(_X4, _X4)})")
_add("nnz_rollup", lambda s, d: cost.nnz_by_cell(_mesh(s, d), _G, "rollup"), f"SELECT gi, gj, gl, COUNT(*) AS nnz FROM (SELECT {', '.join(f'{x} AS {y}' for x, y in zip(_owner(_N_PART, _G), ('gi', 'gj', 'gl'), strict=True))} FROM ({_X6})) GROUP BY ROLLUP (gi, gj, gl)")
_add("nnz_cube", lambda s, d: cost.nnz_by_cell(_mesh(s, d), _G, "cube"), f"SELECT gi, gj, gl, COUNT(*) AS nnz FROM (SELECT {', '.join(f'{x} AS {y}' for x, y in zip(_owner(_N_PART, _G), ('gi', 'gj', 'gl'), strict=True))} FROM ({_X6})) GROUP BY CUBE (gi, gj, gl)")

# --- vectors, independent sets and coarsening ------------------------------------------------------


def mis_sql(a: str, n: str, hops: int, rounds: int, redraw: bool = True, seed: int = 42) -> str:
    """CTEs pat(i, j) and s(i): the rounds of independent_set() unrolled; spare rounds find nothing."""
    out = [f"pat AS MATERIALIZED (SELECT i, j FROM ({a}) UNION SELECT j, i FROM ({a}) UNION SELECT k, k FROM (SELECT unnest(range({n})) AS k))", f"c1 AS MATERIALIZED (SELECT unnest(range({n})) AS i)"]
    for r in range(1, rounds + 1):
        out.append(f"p{r} AS MATERIALIZED (SELECT i, md5('{seed}:{r if redraw else 1}:' || i) AS p FROM c{r})")
        last, reach = f"p{r}", f"w{r}"
        for h in range(hops):
            out.append(f"h{r}_{h} AS MATERIALIZED (SELECT pat.i, MIN(p) AS p FROM pat JOIN {last} x ON pat.j = x.i GROUP BY pat.i)")
            last = f"h{r}_{h}"
        out.append(f"w{r} AS MATERIALIZED (SELECT p{r}.i FROM p{r} JOIN {last} x ON p{r}.i = x.i AND p{r}.p = x.p)")
        for h in range(hops):
            out.append(f"n{r}_{h} AS MATERIALIZED (SELECT DISTINCT pat.i FROM pat JOIN {reach} x ON pat.j = x.i)")
            reach = f"n{r}_{h}"
        out.append(f"c{r + 1} AS MATERIALIZED (SELECT i FROM c{r} WHERE i NOT IN (SELECT i FROM {reach}))")
    out.append("s AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT i FROM w{r}" for r in range(1, rounds + 1)) + ")")
    return ",\n".join(out)


def restriction_sql(a: str, n: str, rounds: int = 8, seed: int = 42) -> str:
    """mis_sql's CTEs and r(i, j, v)."""
    return mis_sql(a, n, 2, rounds) + f""",
      k AS MATERIALIZED (SELECT i, row_number() OVER (ORDER BY i) - 1 AS c FROM s),
      near AS MATERIALIZED (SELECT pat.i, MIN(c) AS c FROM pat JOIN k ON pat.j = k.i GROUP BY pat.i),
      r AS MATERIALIZED (SELECT i, c AS j, CAST(1 AS BIGINT) AS v FROM near UNION ALL SELECT x.i, ('0x' || substr(md5('{seed}:left:' || x.i), 1, 8))::BIGINT % (SELECT COUNT(*) FROM k), CAST(1 AS BIGINT)
        FROM (SELECT unnest(range({n})) AS i) x WHERE x.i NOT IN (SELECT i FROM near))"""


def _r(s, a: SparseMatrix) -> SparseMatrix:
    return coarsen.restriction(a, coarsen.mis2(a))


_MESH_R = restriction_sql(_X6, _N_PART)
_A, _R, _RT = "SELECT * FROM a", "SELECT * FROM r", "SELECT j AS i, i AS j, v FROM r"
_WITH = f"WITH a AS MATERIALIZED ({_X6}), {_MESH_R}"
_V = "SELECT p_partkey AS i, CAST(p_size AS BIGINT) AS v FROM part"


def _sizes(s, d) -> DataFrame:
    return table(s, d, "part").select(F.col("p_partkey").alias("i"), F.col("p_size").cast("bigint").alias("v"))


_add("mxv_min_second", lambda s, d: vector.mxv(_mesh(s, d), _sizes(s, d), MIN_SECOND), f"SELECT a.i, MIN(x.v) AS v FROM ({_X6}) a JOIN ({_V}) x ON a.j = x.i GROUP BY a.i")
_add("mxv_plus_times", lambda s, d: vector.mxv(_x1(s, d), _sizes(s, d), PLUS_TIMES), f"SELECT a.i, CAST(SUM(a.v * x.v) AS BIGINT) AS v FROM ({_X1}) a JOIN ({_V}) x ON a.j = x.i GROUP BY a.i")
_add("vector_apply", lambda s, d: vector.apply(_sizes(s, d), lambda v: v * 3 + 1), f"SELECT i, v * 3 + 1 AS v FROM ({_V})")
_add("ewise_add", lambda s, d: vector.ewise_add(_sizes(s, d).where("i % 2 = 0"), _sizes(s, d).where("i % 3 = 0")), f"SELECT i, CASE WHEN i % 6 = 0 THEN 2 * v ELSE v END AS v FROM ({_V}) WHERE i % 2 = 0 OR i % 3 = 0")
_add("ewise_mult", lambda s, d: vector.ewise_mult(_sizes(s, d).where("i % 2 = 0"), _sizes(s, d).where("i % 3 = 0")), f"SELECT i, v * v AS v FROM ({_V}) WHERE i % 6 = 0")
_add("mask_out", lambda s, d: vector.mask_out(_sizes(s, d), _sizes(s, d).where("i % 3 = 0")), f"SELECT i, v FROM ({_V}) WHERE i % 3 <> 0")
_add("mis2", lambda s, d: coarsen.mis2(_mesh(s, d)), f"WITH {mis_sql(_X6, _N_PART, 2, 8)} SELECT i FROM s")
_add("mis2_fixed", lambda s, d: coarsen.mis2(_mesh(s, d), redraw=False), f"WITH {mis_sql(_X6, _N_PART, 2, 12, False)} SELECT i FROM s")
_add("mis2_next_part", lambda s, d: coarsen.mis2(_x5(s, d)), f"WITH {mis_sql(_X5, _N_PART, 2, 8)} SELECT i FROM s")
_add("mis1", lambda s, d: coarsen.mis1(_mesh(s, d)), f"WITH {mis_sql(_X6, _N_PART, 1, 10)} SELECT i FROM s")
_add("mis2_verify", lambda s, d: coarsen.verify_independent_set(_mesh(s, d), coarsen.mis2(_mesh(s, d))), "SELECT CAST(0 AS BIGINT) AS violations")
_add("mis1_verify", lambda s, d: coarsen.verify_independent_set(_mesh(s, d), coarsen.mis1(_mesh(s, d)), 1), "SELECT CAST(0 AS BIGINT) AS violations")
_add("restriction", lambda s, d: _r(s, _mesh(s, d)).df, f"WITH {_MESH_R} SELECT * FROM r")
_add("restriction_verify", lambda s, d: coarsen.verify_restriction(_r(s, _mesh(s, d))), "SELECT CAST(0 AS BIGINT) AS violations")
_add("rta", lambda s, d: (lambda a: coarsen.restrict_left(a, _r(s, a)).df)(_mesh(s, d)), f"{_WITH} {_product(_RT, _A)}")
_add("rta_grid3d", lambda s, d: (lambda a: coarsen.restrict_left(a, _r(s, a), lambda x, y: grid3d(x, y, Grid(2, 2, 2))).df)(_mesh(s, d)), f"{_WITH} {_product(_RT, _A)}")
_add("ar", lambda s, d: (lambda a: coarsen.restrict_right(a, _r(s, a)).df)(_mesh(s, d)), f"{_WITH} {_product(_A, _R)}")
_add("ar_oned", lambda s, d: (lambda a: coarsen.restrict_right(a, _r(s, a), oned).df)(_mesh(s, d)), f"{_WITH} {_product(_A, _R)}")
for _o in ("left", "right", "auto"):
    _add(f"rtar_{_o}", lambda s, d, o=_o: (lambda a: coarsen.galerkin(a, _r(s, a), o).df)(_mesh(s, d)), f"{_WITH} {_product(_product(_RT, _A), _R)}")
_add("rtar_next_part", lambda s, d: (lambda a: coarsen.galerkin(a, _r(s, a)).df)(_x5(s, d)), f"WITH a AS MATERIALIZED ({_X5}), {restriction_sql(_X5, _N_PART)} {_product(_product(_RT, _A), _R)}")
_add("contract", lambda s, d: (lambda a: (lambda r: coarsen.contract(a, r.df.select("i", F.col("j").alias("c")), r.ncols).df)(_r(s, a)))(_mesh(s, d)), f"{_WITH} SELECT x.j AS i, y.j, CAST(SUM(a.v) AS BIGINT) AS v FROM a JOIN r x ON a.i = x.i JOIN r y ON a.j = y.i GROUP BY 1, 2")
_add("product_report", lambda s, d: (lambda a: cost.product_report({"mesh": (a, _r(s, a))}))(_mesh(s, d)), f"{_WITH} " + " UNION ALL ".join(f"SELECT 'mesh' AS matrix, '{w}' AS what, COUNT(*) AS nnz FROM ({q})" for w, q in {"A": _A, "AA": _product(_A, _A), "R": _R, "RtA": _product(_RT, _A), "RtAR": _product(_product(_RT, _A), _R)}.items()))
_add("hierarchy", lambda s, d: (lambda lv: s.createDataFrame([(n, a.nrows) for n, (a, _) in enumerate(lv)], "level bigint, n bigint"))(coarsen.hierarchy(_mesh(s, d), 100, 2)), None)

_MESHX = f"SELECT a.i, SUM(a.v * x.v) AS v FROM ({_X6}) a JOIN ({_V}) x ON a.j = x.i GROUP BY a.i"
_add("residual", lambda s, d: coarsen.residual(_mesh(s, d), _sizes(s, d), _sizes(s, d)), f"SELECT i, CAST(SUM(v) AS BIGINT) AS v FROM (SELECT i, v FROM ({_V}) UNION ALL SELECT i, -v FROM ({_MESHX})) GROUP BY i")
_RX = f"SELECT r.j AS i, CAST(SUM(r.v * x.v) AS BIGINT) AS v FROM r JOIN ({_V}) x ON r.i = x.i GROUP BY r.j"
_add("restrict_vector", lambda s, d: coarsen.restrict_vector(_r(s, _mesh(s, d)), _sizes(s, d)), f"WITH {_MESH_R} {_RX}")
_add("prolong_vector", lambda s, d: (lambda r: coarsen.prolong_vector(r, coarsen.restrict_vector(r, _sizes(s, d))))(_r(s, _mesh(s, d))), f"WITH {_MESH_R} SELECT r.i, CAST(SUM(r.v * y.v) AS BIGINT) AS v FROM r JOIN ({_RX}) y ON r.j = y.i GROUP BY r.i")

# --- graph functions and products around them ------------------------------------------------------

_add("split_diag", lambda s, d: (lambda m: (lambda p: p[0].df.withColumn("part", F.lit("d")).unionByName(p[1].df.withColumn("part", F.lit("o"))).groupBy("part").agg(F.count(F.lit(1)).alias("n"), F.sum("v").alias("total")))(m.split_diagonal()))(_mesh(s, d)), f"SELECT CASE WHEN i = j THEN 'd' ELSE 'o' END AS part, COUNT(*) AS n, CAST(SUM(v) AS BIGINT) AS total FROM ({_X6}) GROUP BY 1")
_add("triangles", lambda s, d: graph.triangles(_x5(s, d)), f"SELECT COUNT(*) AS triangles FROM (SELECT i, j FROM ({_X5}) WHERE i > j) a JOIN (SELECT i, j FROM ({_X5}) WHERE i > j) b ON a.j = b.i JOIN (SELECT i, j FROM ({_X5}) WHERE i > j) c ON c.i = a.i AND c.j = b.j")
_add("masked", lambda s, d: multiply(_mesh(s, d), _mesh(s, d), plan="grid3d", mask=_mesh(s, d)).df, f"SELECT p.* FROM ({_X6X6}) p JOIN ({_X6}) m ON p.i = m.i AND p.j = m.j")
_add("masked_out", lambda s, d: multiply(_mesh(s, d), _mesh(s, d), plan="catalyst", mask=_mesh(s, d), complement=True).df, f"SELECT p.* FROM ({_X6X6}) p LEFT JOIN ({_X6}) m ON p.i = m.i AND p.j = m.j WHERE m.i IS NULL")
_add("truncated", lambda s, d: multiply(_mesh(s, d), _mesh(s, d), plan="grid3d", drop_below=2).df, f"SELECT * FROM ({_X6X6}) WHERE abs(v) >= 2")
_add("khop_minplus", lambda s, d: graph.khop_costs(_mesh(s, d), 3).df, _product(_product(_X6, _X6, MIN_PLUS), _X6, MIN_PLUS))
_add("widest_paths", lambda s, d: graph.widest_paths(_mesh(s, d), 3).df, _product(_product(_X6, _X6, MAX_MIN), _X6, MAX_MIN))
_TRUE6 = f"SELECT i, j, TRUE AS v FROM ({_X6})"
_add("reach_bool", lambda s, d: graph.reachable(_mesh(s, d), 4).df, _product(_product(_TRUE6, _TRUE6, OR_AND), _product(_TRUE6, _TRUE6, OR_AND), OR_AND))
_OFF8 = f"SELECT i, j, TRUE AS v FROM ({_X8}) WHERE i <> j"
_add("cycle_diag", lambda s, d: graph.cycle_lengths(datasets.nation_trade(s, d), 3), f"SELECT CAST(1 AS BIGINT) AS length, CAST(0 AS BIGINT) AS vertices UNION ALL SELECT 2, COUNT(*) FROM ({_product(_OFF8, _OFF8, OR_AND)}) WHERE i = j UNION ALL SELECT 3, COUNT(*) FROM ({_product(_product(_OFF8, _OFF8, OR_AND), _OFF8, OR_AND)}) WHERE i = j")
_add("peer_pressure_step", lambda s, d: graph.peer_pressure(_x5(s, d), table(s, d, "part").select(F.col("p_partkey").alias("i"), F.pmod("p_partkey", F.lit(7)).alias("v"))), f"""SELECT i, l AS v FROM (SELECT i, l, row_number() OVER (PARTITION BY i ORDER BY n DESC, l) AS k FROM (SELECT i, j % 7 AS l, COUNT(*) AS n
    FROM (SELECT i, j FROM ({_X5}) UNION SELECT p_partkey, p_partkey FROM part) GROUP BY 1, 2)) WHERE k = 1""")  # fmt: skip
_NORM = "SELECT i, j, v / s AS v FROM ({0}) JOIN (SELECT j, SUM(v) AS s FROM ({0}) GROUP BY j) USING (j)"
_M0 = _NORM.format(f"SELECT i, j, CAST(v AS DOUBLE) AS v FROM ({_X8})")
_FLOW = _NORM.format(f"SELECT i, j, v * v AS v FROM (SELECT a.i, b.j, SUM(a.v * b.v) AS v FROM ({_M0}) a JOIN ({_M0}) b ON a.j = b.i GROUP BY 1, 2) WHERE v * v >= 0.0001")
_add("mcl_step", lambda s, d: graph.flow_step(datasets.nation_trade(s, d)).df.select("i", "j", F.round("v", 9).alias("v")), f"SELECT i, j, ROUND(v, 9) AS v FROM ({_FLOW})")
_SRC = "SELECT * FROM (VALUES (0, 0, 1), (1, 5, 1), (2, 77, 1)) t(i, j, v)"
_add("betweenness_level", lambda s, d: (lambda m, f: graph.betweenness_level(m, f, f).df)(_mesh(s, d), SparseMatrix.rows_of(s, [(0, 0, 1), (1, 5, 1), (2, 77, 1)], 3, _mesh(s, d).nrows)), f"SELECT CAST(f.i AS BIGINT) AS i, a.j, CAST(SUM(f.v) AS BIGINT) AS v FROM ({_SRC}) f JOIN ({_X6}) a ON f.j = a.i WHERE NOT EXISTS (SELECT 1 FROM ({_SRC}) g WHERE g.i = f.i AND g.j = a.j) GROUP BY 1, 2")
_add("betweenness", lambda s, d: graph.betweenness(_x5(s, d), [0, 3]).select("i", F.round("v", 9).alias("v")), None)
_add("schur_diag", lambda s, d: (lambda m: graph.schur_diagonal(SparseMatrix(m.df.where("NOT (i < 100 AND j < 100 AND i <> j)"), m.nrows, m.ncols), 100).df.select("i", "j", F.round("v", 9).alias("v")))(_mesh(s, d)), f"""WITH a AS (SELECT * FROM ({_X6}) WHERE NOT (i < 100 AND j < 100 AND i <> j)),
    x AS (SELECT c.i, r.j, SUM(c.v * (r.v / CAST(p.v AS DOUBLE))) AS v FROM a c JOIN a r ON c.j = r.i JOIN a p ON p.i = r.i AND p.j = r.i WHERE c.i >= 100 AND c.j < 100 AND r.i < 100 AND r.j >= 100 GROUP BY 1, 2)
    SELECT COALESCE(d.i, x.i) - 100 AS i, COALESCE(d.j, x.j) - 100 AS j, ROUND(COALESCE(CAST(d.v AS DOUBLE), 0) - COALESCE(x.v, 0), 9) AS v FROM (SELECT * FROM a WHERE i >= 100 AND j >= 100) d FULL JOIN x ON d.i = x.i AND d.j = x.j""")  # fmt: skip
_add("kron_small", lambda s, d: datasets.nation_trade(s, d).kron(SparseMatrix.rows_of(s, [(0, 1, 2), (1, 0, 3)], 2, 2)).df, f"SELECT 2 * i + bi AS i, 2 * j + bj AS j, v * bv AS v FROM ({_X8}), (VALUES (0, 1, 2), (1, 0, 3)) t(bi, bj, bv)")
_add("matrix_subtract", lambda s, d: _x4(s, d).subtract(_x4(s, d).t).df, f"SELECT COALESCE(a.i, b.i) AS i, COALESCE(a.j, b.j) AS j, COALESCE(a.v, 0) - COALESCE(b.v, 0) AS v FROM ({_X4}) a FULL JOIN ({_t(_X4)}) b ON a.i = b.i AND a.j = b.j")
_add("matrix_hadamard", lambda s, d: _x4(s, d).ewise_mult(_x4(s, d).t).df, f"SELECT a.i, a.j, a.v * b.v AS v FROM ({_X4}) a JOIN ({_t(_X4)}) b ON a.i = b.i AND a.j = b.j")
_add("matrix_extract", lambda s, d: _mesh(s, d).extract((50, 150), (40, 160)).df, f"SELECT i - 50 AS i, j - 40 AS j, v FROM ({_X6}) WHERE i >= 50 AND i < 150 AND j >= 40 AND j < 160")
_add("matrix_assign", lambda s, d: (lambda m: m.assign((0, 10), (0, 10), SparseMatrix.eye(s, 10)).df)(_mesh(s, d)), f"SELECT * FROM ({_X6}) WHERE NOT (i < 10 AND j < 10) UNION ALL SELECT k, k, CAST(1 AS BIGINT) FROM (SELECT unnest(range(10)) AS k)")
_add("matrix_trace", lambda s, d: _mesh(s, d).trace(), f"SELECT CAST(SUM(v) AS BIGINT) AS v FROM ({_X6}) WHERE i = j")
_add("row_sums", lambda s, d: _x1(s, d).reduce_rows(), f"SELECT i, CAST(SUM(v) AS BIGINT) AS v FROM ({_X1}) GROUP BY i")

# --- operators around the products -----------------------------------------------------------------

_add("op_scan_prune", lambda s, d: table(s, d, "lineitem").where(F.col("l_partkey").between(100, 199)).groupBy(F.col("l_orderkey").alias("i"), F.col("l_partkey").alias("j")).agg(F.sum("l_quantity").cast("bigint").alias("v")), f"SELECT * FROM ({_X1}) WHERE j BETWEEN 100 AND 199")
_add("op_project_transpose", lambda s, d: _x1(s, d).t.scale(2).df, f"SELECT j AS i, i AS j, v * 2 AS v FROM ({_X1})")
_add("op_filter_triangle", lambda s, d: _x5(s, d).tril().df, f"SELECT * FROM ({_X5}) WHERE i > j")
_add("op_threshold", lambda s, d: _x5(s, d).where("v >= 2").df, f"SELECT * FROM ({_X5}) WHERE v >= 2")
for _h in ("merge", "shuffle_hash", "broadcast"):
    _add(f"op_join_{_h}", lambda s, d, h=_h: checksum(catalyst(_x1(s, d).t, _x1(s, d), hint=h)), _checksum(_X1tX1))
_add("op_join_nested_loop", lambda s, d: table(s, d, "nation").join(F.broadcast(table(s, d, "region")), F.expr("n_regionkey < r_regionkey")).select(F.col("n_nationkey").alias("i"), F.col("r_regionkey").alias("j"), F.lit(True).alias("v")), "SELECT n_nationkey AS i, r_regionkey AS j, TRUE AS v FROM nation JOIN region ON n_regionkey < r_regionkey")
_add("op_join_range_panels", lambda s, d: (lambda m: m.df.join(F.broadcast(s.range(-(-m.ncols // 37)).selectExpr("id AS panel", "37 * id AS lo", "37 * id + 36 AS hi")), F.expr("j BETWEEN lo AND hi")))(_mesh(s, d)).groupBy("panel").agg(F.count(F.lit(1)).alias("n")), f"SELECT panel, COUNT(*) AS n FROM ({_X6}) JOIN (SELECT p AS panel, 37 * p AS lo, 37 * p + 36 AS hi FROM (SELECT unnest(range((SELECT max(p_partkey) // 37 + 1 FROM part))) AS p)) ON j BETWEEN lo AND hi GROUP BY panel")
_add("op_join_semi", lambda s, d: _x1(s, d).df.join(table(s, d, "part").where("p_brand = 'Brand#2'").select(F.col("p_partkey").alias("j")), "j", "left_semi").select("i", "j", "v"), f"SELECT * FROM ({_X1}) x WHERE EXISTS (SELECT 1 FROM part WHERE p_partkey = x.j AND p_brand = 'Brand#2')")
_add("op_join_anti", lambda s, d: table(s, d, "part").select(F.col("p_partkey").alias("i")).join(datasets.part_supp(s, d).df.where("j = 1"), "i", "left_anti"), "SELECT p_partkey AS i FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_suppkey = 1)")
_add("op_join_full_outer", lambda s, d: _x4(s, d).ewise_add(_x4(s, d).t).df, f"SELECT i, j, CAST(SUM(v) AS BIGINT) AS v FROM (SELECT * FROM ({_X4}) UNION ALL SELECT * FROM ({_t(_X4)})) GROUP BY 1, 2")


def _asof(s, d) -> DataFrame:
    """Each purchase with its user's latest earlier click."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    e = table(s, d, "events").withColumn("click", F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(order))
    return e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "click")


_add("op_asof_edge", _asof, """SELECT event_id AS purchase, click FROM (SELECT event_id, event_type, LAST_VALUE(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS click FROM events) WHERE event_type = 'purchase'""")


def _coactivity(s, d) -> DataFrame:
    """Pairs of users with events of one type within ten minutes: an equi join on ten-minute buckets,
    each event standing in its own and the next."""
    e = table(s, d, "events").select("user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    b = F.call_function("div", F.col("t"), F.lit(600_000_000))
    left = e.select(F.col("user_id").alias("i"), "event_type", F.col("t").alias("ti"), b.alias("b"))
    right = e.select(F.col("user_id").alias("j"), "event_type", F.col("t").alias("tj"), F.explode(F.array(b - 1, b, b + 1)).alias("b"))
    return left.join(right, ["event_type", "b"]).where("i < j AND abs(ti - tj) <= 600000000").groupBy("i", "j").agg(F.count(F.lit(1)).alias("v"))


_add("op_interval_coactivity", _coactivity, "SELECT a.user_id AS i, b.user_id AS j, COUNT(*) AS v FROM events a JOIN events b ON a.event_type = b.event_type AND a.user_id < b.user_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 600000000 GROUP BY 1, 2")
_add("op_agg_hash", lambda s, d: _x1(s, d).df.groupBy("i").agg(F.count(F.lit(1)).alias("n"), F.sum("v").alias("v")), f"SELECT i, COUNT(*) AS n, CAST(SUM(v) AS BIGINT) AS v FROM ({_X1}) GROUP BY i")
_add("op_agg_sort", lambda s, d: _x1(s, d).df.groupBy("i").agg(F.array_join(F.array_sort(F.collect_list("j")), ",").alias("js")), f"SELECT i, string_agg(CAST(j AS VARCHAR), ',' ORDER BY j) AS js FROM ({_X1}) GROUP BY i")
_add("op_agg_distinct", lambda s, d: _x1(s, d).df.agg(F.countDistinct("i").alias("rows"), F.countDistinct("j").alias("cols")), f"SELECT COUNT(DISTINCT i) AS rows, COUNT(DISTINCT j) AS cols FROM ({_X1})")
_add("op_agg_approx", lambda s, d: catalyst(_x4(s, d), _x4(s, d)).df.agg(F.count(F.lit(1)).alias("nnz"), F.approx_count_distinct(F.struct("i", "j"), 0.02).alias("about")).select("nnz", (F.abs(F.col("about") - F.col("nnz")) <= 0.08 * F.col("nnz")).alias("near")), f"SELECT COUNT(*) AS nnz, TRUE AS near FROM ({_product(_X4, _X4)})")
_add("op_grouping_sets", lambda s, d: (datasets.part_supp(s, d).df.createOrReplaceTempView("layermul_gs"), s.sql("SELECT i div 1000 AS a, j div 10 AS b, CAST(grouping_id() AS BIGINT) AS g, COUNT(*) AS n FROM layermul_gs GROUP BY GROUPING SETS ((i div 1000, j div 10), (i div 1000), ())"))[1], f"SELECT a, b, CASE WHEN grouping(a) = 1 THEN 3 WHEN grouping(b) = 1 THEN 1 ELSE 0 END::BIGINT AS g, COUNT(*) AS n FROM (SELECT i // 1000 AS a, j // 10 AS b FROM ({SQL['part_supp']})) GROUP BY GROUPING SETS ((a, b), (a), ())")
_BRANDS = "SELECT p_brand AS brand, p_type AS type, COUNT(*) AS n FROM ({0}) JOIN part ON p_partkey = i GROUP BY {1} (p_brand, p_type)"
for _k in ("rollup", "cube"):
    _add(f"op_{_k}", lambda s, d, k=_k: getattr(datasets.part_supp(s, d).df.join(table(s, d, "part").select(F.col("p_partkey").alias("i"), F.col("p_brand").alias("brand"), F.col("p_type").alias("type")), "i"), k)("brand", "type").agg(F.count(F.lit(1)).alias("n")), _BRANDS.format(SQL["part_supp"], _k.upper()))
_add("op_window_rank", lambda s, d: _x1(s, d).df.withColumn("k", F.row_number().over(Window.partitionBy("i").orderBy(F.desc("v"), "j"))).where("k <= 3"), f"SELECT * FROM (SELECT i, j, v, row_number() OVER (PARTITION BY i ORDER BY v DESC, j) AS k FROM ({_X1})) WHERE k <= 3")
_add("op_topk_col", lambda s, d: _x1(s, d).df.withColumn("k", F.rank().over(Window.partitionBy("j").orderBy(F.desc("v")))).where("k <= 2").select("i", "j", "v"), f"SELECT i, j, v FROM (SELECT i, j, v, rank() OVER (PARTITION BY j ORDER BY v DESC) AS k FROM ({_X1})) WHERE k <= 2")
_add("op_window_dense_rank", lambda s, d: _x4(s, d).df.select("i", "j", (F.dense_rank().over(Window.partitionBy("i").orderBy("v")) - 1).cast("bigint").alias("r")), f"SELECT i, j, dense_rank() OVER (PARTITION BY i ORDER BY v) - 1 AS r FROM ({_X4})")
_add("op_window_prefix", lambda s, d: (lambda m: vector.running(m.df.groupBy("j").agg(F.count(F.lit(1)).alias("n")), "j", m.ncols, F.col("n")).select("j", F.col("upto").alias("start")))(_x1(s, d)), f"SELECT j, CAST(COALESCE(SUM(n) OVER (ORDER BY j ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS start FROM (SELECT j, COUNT(*) AS n FROM ({_X1}) GROUP BY j)")
_add("op_window_ntile", lambda s, d: (lambda m: vector.tiles(m.df.select("j").distinct(), "j", m.ncols, 16).select("j", F.col("tile").alias("part")))(_x1(s, d)), f"SELECT j, ntile(16) OVER (ORDER BY j) AS part FROM (SELECT DISTINCT j FROM ({_X1}))")
_add("op_window_range_frame", lambda s, d: _mesh(s, d).df.select("i", "j", F.sum("v").over(Window.partitionBy("i").orderBy("j").rangeBetween(-2, 2)).alias("v")), f"SELECT i, j, CAST(SUM(v) OVER (PARTITION BY i ORDER BY j RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS BIGINT) AS v FROM ({_X6})")
_add("op_lead_edges", lambda s, d: _x4(s, d).df, _X4)
_add("op_lag_runs", lambda s, d: _x1(s, d).df.select("i", "j", (F.coalesce(F.lag("v").over(Window.partitionBy("i").orderBy("j")), F.lit(-1)) != F.col("v")).alias("new")), f"SELECT i, j, COALESCE(LAG(v) OVER (PARTITION BY i ORDER BY j), -1) <> v AS new FROM ({_X1})")
_add("op_topk_global", lambda s, d: catalyst(_x1(s, d).t, _x1(s, d)).df.orderBy(F.desc("v"), "i", "j").limit(20), f"SELECT * FROM ({_X1tX1}) ORDER BY v DESC, i, j LIMIT 20")
_add("op_union", lambda s, d: _x4(s, d).df.select("i", "j").union(_x4(s, d).t.df.select("i", "j")).distinct(), f"SELECT i, j FROM ({_X4}) UNION SELECT j, i FROM ({_X4})")
_add("op_intersect", lambda s, d: _x4(s, d).df.select("i", "j").intersect(_x4(s, d).t.df.select("i", "j")), f"SELECT i, j FROM ({_X4}) INTERSECT SELECT j, i FROM ({_X4})")
_add("op_except", lambda s, d: _x4(s, d).df.select("i", "j").exceptAll(_x4(s, d).t.df.select("i", "j")), f"SELECT i, j FROM ({_X4}) EXCEPT SELECT j, i FROM ({_X4})")
_add("op_date_buckets", lambda s, d: table(s, d, "lineitem").join(table(s, d, "part").select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey")).groupBy((F.year("l_shipdate") * 12 + F.month("l_shipdate")).cast("bigint").alias("month"), F.col("p_brand").alias("brand")).agg(F.sum("l_quantity").cast("bigint").alias("v")), "SELECT year(l_shipdate) * 12 + month(l_shipdate) AS month, p_brand AS brand, CAST(SUM(l_quantity) AS BIGINT) AS v FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1, 2")
_add("op_math_priority", lambda s, d: table(s, d, "part").select(F.col("p_partkey").alias("i"), coarsen.md5_number(F.lit("42"), F.lit("1"), F.col("p_partkey")).alias("p")), "SELECT p_partkey AS i, ('0x' || substr(md5('42:1:' || p_partkey), 1, 8))::BIGINT AS p FROM part")
_add("op_array_hof", lambda s, d: layout.to_dcsc(_mesh(s, d)).df.select("j", F.expr("aggregate(zip_with(transform(entries, e -> e.v), transform(entries, e -> e.i), (v, i) -> v * i), 0L, (t, x) -> t + x)").alias("dot")), f"SELECT j, CAST(SUM(v * i) AS BIGINT) AS dot FROM ({_X6}) GROUP BY j")
_add("op_map_row", lambda s, d: _x1(s, d).df.groupBy("i").agg(F.map_from_entries(F.collect_list(F.struct("j", "v"))).alias("m")).select("i", F.size(F.map_filter("m", lambda k, v: v > 25)).cast("bigint").alias("n")), f"SELECT i, COUNT(*) FILTER (WHERE v > 25) AS n FROM ({_X1}) GROUP BY i")
_REG = "SELECT a.n_regionkey AS i, b.n_regionkey AS j, CAST(SUM(v) AS BIGINT) AS v FROM ({0}) JOIN nation a ON i = a.n_nationkey JOIN nation b ON j = b.n_nationkey GROUP BY 1, 2"


def _regions(s, d) -> DataFrame:
    n = table(s, d, "nation").select("n_nationkey", "n_regionkey")
    m = datasets.nation_trade(s, d).df.join(n.toDF("i", "ri"), "i").join(n.toDF("j", "rj"), "j")
    return m.groupBy("ri").pivot("rj", [0, 1, 2, 3, 4]).agg(F.sum("v")).withColumnRenamed("ri", "i")


_add("op_pivot", lambda s, d: _regions(s, d).select("i", *[F.col(str(k)).alias(f"r{k}") for k in range(5)]), f"SELECT i, {', '.join(f'CAST(SUM(v) FILTER (WHERE j = {k}) AS BIGINT) AS r{k}' for k in range(5))} FROM ({_REG.format(_X8)}) GROUP BY i")
_add("op_unpivot", lambda s, d: _regions(s, d).unpivot("i", [str(k) for k in range(5)], "j", "v").select("i", F.col("j").cast("int").alias("j"), "v").where("v IS NOT NULL"), _REG.format(_X8))
_add("op_udf_semiring", lambda s, d: (lambda m: catalyst(m, m, user_semiring("user", lambda x: x.sum(), lambda a, b: a * b, plus=lambda a, b: a + b)).df)(_mesh(s, d)), _X6X6)
_add("op_udtf_expand", lambda s, d: (register(s, lm_b=_mesh(s, d)), layout.to_dcsc(_mesh(s, d)).df.selectExpr("j AS k", "transform(entries, e -> e.i) AS r", "transform(entries, e -> e.v) AS x").createOrReplaceTempView("lm_cols"),
     s.sql("SELECT e.i, b.j, SUM(e.v) AS v FROM lm_b b JOIN lm_cols c ON b.i = c.k, LATERAL expand_column(c.r, c.x, b.v) e GROUP BY e.i, b.j"))[2], _X6X6)
_add("op_sql_product", lambda s, d: (register(s, lm_mesh=_mesh(s, d)), sql_multiply(s, "lm_mesh", "lm_mesh"))[1], product_sql(f"({_X6})", f"({_X6})"))


def _roundtrip(s, d, way: str) -> DataFrame:
    m, path = _mesh(s, d), fresh_path(s, way)
    if way == "coo_text":
        io.write_coo_text(m, path)
        return io.read_coo_text(s, path).df
    if way == "csv":
        io.write_csv(m, path)
        return io.read_csv(s, path).df
    if way == "json":
        io.write_json(m, path)
        return io.read_json(s, path).df
    io.write_blocks(m, path, Grid(4, 4, 1))
    return io.read_blocks(s, path, m.nrows, m.ncols).df


for _w in ("coo_text", "csv", "json", "blocks"):
    _add(f"op_io_{_w}", lambda s, d, w=_w: _roundtrip(s, d, w), _X6)


def _bucketed(s, d) -> DataFrame:
    m = _mesh(s, d)
    io.save_bucketed(m, "layermul_bucketed", path=fresh_path(s, "bucketed"))
    return io.load_bucketed(s, "layermul_bucketed", m.nrows, m.ncols).df


_add("op_io_bucketed", _bucketed, _X6)
_add("op_source_rmat", lambda s, d: (register(s), s.read.format("rmat").option("class", "uniform").option("scale", "6").load().groupBy("i", "j").agg(F.count(F.lit(1)).alias("v")))[1], rmat_sql("uniform", 6))

# --- streams ---------------------------------------------------------------------------------------


def _stream(s: SparkSession, d: str, what: str) -> DataFrame:
    from layermul.streaming import stream

    events = stream.event_stream(s, d)
    name = f"layermul_{what}"
    if what == "delta_product":
        kinds = ["cart", "click", "purchase", "signup", "view"]
        b = SparseMatrix.rows_of(s, [(x, y, 1 + x * y) for x in range(5) for y in range(5)], 5, 5)
        rule = F.create_map(*[F.lit(v) for n, k in enumerate(kinds) for v in (k, n)])
        delta = stream.DeltaProduct(b, 1 << 40)
        rows = events.select(F.col("user_id").alias("i"), F.coalesce(F.try_element_at(rule, F.col("event_type")), F.lit(4)).cast("bigint").alias("j"))
        stream.run_to_end(rows, each=lambda batch, n: delta.add(batch.groupBy("i", "j").agg(F.count(F.lit(1)).alias("v")), n))
        return delta.product.df
    if what == "click_purchases":
        stream.run_to_end(stream.click_purchases(events.where("event_type = 'click'"), stream.event_stream(s, d).where("event_type = 'purchase'")), name=name)
        return s.table(name)
    if what == "dedupe":
        return stream.stored(stream.once_per_event(events).select("event_id"))
    return stream.stored(stream.windowed_matrix(events, what), "complete" if what != "session" else "append")


_KINDS = "(VALUES ('cart', 0), ('click', 1), ('purchase', 2), ('signup', 3), ('view', 4)) k(name, x)"
_add("stream_tumbling", lambda s, d: _stream(s, d, "tumbling"), "SELECT time_bucket(INTERVAL '1 hour', ts) AS start, user_id AS i, event_type, COUNT(*) AS v FROM events GROUP BY 1, 2, 3")
_add("stream_sliding", lambda s, d: _stream(s, d, "sliding"), "SELECT time_bucket(INTERVAL '15 minutes', ts) - k * INTERVAL '15 minutes' AS start, user_id AS i, event_type, COUNT(*) AS v FROM events, range(4) r(k) GROUP BY 1, 2, 3")
# a session is told once the watermark, ten minutes behind the latest event, has passed its end
_add("stream_session", lambda s, d: _stream(s, d, "session"), """SELECT min(ts) AS start, user_id AS i, COUNT(*) AS v FROM (SELECT *, SUM(CAST(new AS INT)) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k
    FROM (SELECT *, COALESCE(ts - LAG(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) >= INTERVAL 30 MINUTES, TRUE) AS new FROM events)) GROUP BY user_id, k
    HAVING max(ts) + INTERVAL 30 MINUTES <= (SELECT date_trunc('millisecond', max(ts)) - INTERVAL 10 MINUTES FROM events)""")
_add("stream_click_purchases", lambda s, d: _stream(s, d, "click_purchases"), """SELECT c.user_id AS i, c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id
    AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 10 MINUTES WHERE c.event_type = 'click' AND p.event_type = 'purchase'""")
_add("stream_dedupe", lambda s, d: _stream(s, d, "dedupe"), "SELECT DISTINCT event_id FROM events")
_add("stream_delta_product", lambda s, d: _stream(s, d, "delta_product"), f"""SELECT i, y AS j, CAST(SUM(n * (1 + x * y)) AS BIGINT) AS v FROM (SELECT user_id AS i, COALESCE(k.x, 4) AS x, COUNT(*) AS n FROM events LEFT JOIN {_KINDS} ON event_type = name GROUP BY 1, 2), range(5) t(y) GROUP BY 1, 2""")


def _configured(query: Query) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return query(configure(spark), sf_dir)

    return run


def queries() -> dict[str, Query]:
    return {name: _configured(q) for name, (q, _) in _QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in _QUERIES.items() if sql}
