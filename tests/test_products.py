"""Plans against dense products on hand-made cases, against each other, and against exact measures."""

import itertools

import numpy as np
import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st

from layermul.matrix import AffinePermutation, SparseMatrix, digest_permutation, permute_by
from layermul.functions.udfs import _fold_runs, user_semiring
from layermul.operators import cost, kernels, layout, merge
from layermul.operators.graph import power
from layermul.plans import multiply as plans
from layermul.plans import planner
from layermul.plans.grid import Grid, GridConfig, _murmur_int, partition_keys
from layermul.plans.multiply import TooMuchWork, catalyst, cell_points, grid2d, grid3d, heavy_inner, local_sql, multiply, oned
from layermul.plans.planner import ProductStats, choose_plan, comm_asymptotic, comm_model, estimate_nnz_c, measure, overlap_gain
from layermul.semiring import MIN_PLUS, SEMIRINGS
from layermul.sources.generators import CLASSES, rmat

GRIDS = [(1, 1, 1), (2, 2, 1), (2, 3, 1), (2, 2, 2), (1, 1, 4), (3, 2, 5), (8, 8, 1)]


def entries(m):
    return {(r["i"], r["j"]): r["v"] for r in m.df.collect()}


def dense_product(a, b, plus=lambda x, y: x + y, times=lambda x, y: x * y):
    out = {}
    for (i, k), x in a.items():
        for (k2, j), y in b.items():
            if k == k2:
                out[i, j] = plus(out[i, j], times(x, y)) if (i, j) in out else times(x, y)
    return out


def matrix(spark, cells, m, n):
    return SparseMatrix.rows_of(spark, [(i, j, v) for (i, j), v in cells.items()], m, n)


CASES = {
    "empty": ({}, {}, 4, 4, 4),
    "row_by_column": ({(0, k): k + 1 for k in range(5)}, {(k, 0): 2 for k in range(5)}, 1, 5, 1),
    "column_by_row": ({(k, 0): k for k in range(5)}, {(0, k): 1 for k in range(4)}, 5, 1, 4),
    "empty_edges": ({(0, 0): 1, (1, 2): 3}, {(0, 1): 5, (2, 1): 7}, 6, 5, 6),
    "explicit_zero_and_cancelling": ({(0, 0): 1, (0, 1): 1, (1, 1): 0}, {(0, 0): 4, (1, 0): -4, (1, 2): 2}, 3, 3, 3),
    "hub": ({(i, 3): i for i in range(7)} | {(2, k): 1 for k in range(7)}, {(3, j): j for j in range(6)}, 7, 7, 6),
}


@pytest.mark.parametrize("name", CASES)
def test_all_plans_on_mini_cases(spark, name):
    a, b, m, k, n = CASES[name]
    one, two, want = matrix(spark, a, m, k), matrix(spark, b, k, n), dense_product(a, b)
    assert entries(catalyst(one, two)) == want
    assert entries(oned(one, two)) == entries(oned(one, two, by="col")) == want
    assert entries(grid2d(one, two, 2, 3, block=1)) == want
    for g in ((2, 2, 2), (3, 2, 5)):
        assert entries(grid3d(one, two, Grid(*g))) == want
    assert entries(kernels.heap_kernel(one, two, Grid(2, 1, 2))) == want
    assert entries(kernels.dense_acc_kernel(one, two, Grid(1, 2, 1))) == want


@pytest.mark.parametrize("grid", GRIDS)
@pytest.mark.parametrize("block", [1, 7, None])
def test_grids_and_widths_agree(spark, grid, block):
    a = rmat(spark, "community", 5)
    plain = catalyst(a, a).df
    got = grid3d(a, a, Grid(*grid), block=block).df
    assert got.exceptAll(plain).isEmpty() and plain.exceptAll(got).isEmpty()


def test_staged_merges_agree(spark):
    a = rmat(spark, "skewed", 5)
    want = entries(catalyst(a, a))
    assert entries(grid2d(a, a, 2, 2, mode="staged", merge="stage")) == entries(grid2d(a, a, 2, 2, mode="staged", merge="end")) == want


@settings(max_examples=8, deadline=None, suppress_health_check=[HealthCheck.function_scoped_fixture])
@given(st.dictionaries(st.tuples(st.integers(0, 6), st.integers(0, 6)), st.integers(-9, 9), max_size=20), st.sampled_from(GRIDS))
def test_random_squares(spark, cells, grid):
    a = matrix(spark, cells, 7, 7)
    assert entries(grid3d(a, a, Grid(*grid))) == dense_product(cells, cells)


def test_semirings_on_a_grid(spark):
    cells = {(i, j): (3 * i + 5 * j) % 7 - 2 for i, j in itertools.product(range(5), range(5)) if (i + j) % 3}
    a = matrix(spark, cells, 5, 5)
    rules = {"min_plus": (min, lambda x, y: x + y), "max_min": (max, min), "min_second": (min, lambda x, y: y), "min_first": (min, lambda x, y: x), "plus_pair": (lambda x, y: x + y, lambda x, y: 1), "max_times": (max, lambda x, y: x * y)}
    for name, (plus, times) in rules.items():
        assert entries(grid3d(a, a, Grid(2, 2, 2), SEMIRINGS[name])) == dense_product(cells, cells, plus, times)
    assert entries(kernels.heap_kernel(a, a, semiring=MIN_PLUS)) == entries(kernels.dense_acc_kernel(a, a, semiring=MIN_PLUS))


def test_masks_limits_and_small_results(spark):
    a = rmat(spark, "uniform", 4)
    full = entries(catalyst(a, a))
    held = set(entries(a))
    assert entries(multiply(a, a, mask=a)) == {k: v for k, v in full.items() if k in held}
    assert entries(multiply(a, a, mask=a, complement=True)) == {k: v for k, v in full.items() if k not in held}
    assert entries(multiply(a, a, drop_below=3)) == {k: v for k, v in full.items() if abs(v) >= 3}
    with pytest.raises(TooMuchWork):
        multiply(a, a, max_flops=10)


def test_invariants(spark):
    a, b = rmat(spark, "skewed", 5, 1), rmat(spark, "uniform", 5, 2)
    left = catalyst(a, b)
    assert entries(left.t) == entries(catalyst(b.t, a.t))
    p = AffinePermutation.near(32, 5, 3)
    assert entries(catalyst(a.permute(p), b.permute(p)).unpermute(p)) == entries(left)
    flops = cost.flops(a, b).first()["flops"]
    for g in (Grid(2, 2, 2), Grid(1, 1, 4)):
        row = cost.memory_factor(a, b, g).first()
        assert row["nnz_c"] == left.nnz() <= row["nnz_int"] <= row["flops"] == flops
        assert sum(r["flops"] for r in cost.work_by_cell(a, b, g).collect()) == flops
        words = {r["phase"]: r["total"] for r in cost.words_moved(a, b, g).collect()}
        assert words["a_broadcast"] == a.nnz() * (g.pc - 1) and words["b_broadcast"] == b.nnz() * (g.pr - 1)
        for kind in ("1d", "2d", "3d"):
            assert sum(r["points"] for r in cost.assign_work(a, b, g, kind).collect()) == flops


# Measured totals of the survey, for scale 10 and seed 42.
GOLDENS = [
    ("uniform", (4, 4, 1), 48750, 0, 229107, 0),
    ("uniform", (2, 2, 4), 16250, 12297, 250626, 189649),
    ("skewed", (2, 2, 4), 12049, 8001, 385934, 263130),
    ("skewed", (1, 1, 16), 0, 10744, 505988, 453730),
]


@pytest.mark.parametrize("cls, grid, cast, deal, made, moved", GOLDENS)
def test_goldens(spark, cls, grid, cast, deal, made, moved):
    a = rmat(spark, cls, 10)
    words = {r["phase"]: r["total"] for r in cost.words_moved(a, a, Grid(*grid)).collect()}
    assert (words["a_broadcast"], words["b_deal"], words["c_exchange"]) == (cast, deal, moved)
    assert cost.memory_factor(a, a, Grid(*grid)).first()["nnz_int"] == made


def test_more_layers_trade_input_for_output_traffic():
    s = ProductStats(1 << 20, 1 << 20, 1 << 20, 16 << 20, 16 << 20, 256 << 20)
    inputs = [comm_asymptotic(s, 256, c, 64)[1] - s.flops / 256 for c in (1, 4, 16)]
    assert inputs == sorted(inputs, reverse=True)
    assert comm_model(s, 256, 16, 64) < comm_model(s, 256, 1, 64)
    assert overlap_gain(0.5) == 2 and overlap_gain(0.8) == pytest.approx(1.25)


def test_planner(spark):
    a = rmat(spark, "community", 5)
    s = measure(a, a)
    assert s.nnz_a == a.nnz() and choose_plan(s, 8)[0] == "oned_broadcast"
    for want, stats in {
        ("oned_broadcast", None): ProductStats(10**9, 10**9, 10**9, 10**10, 1000, 10**6),
        ("oned_broadcast_a", None): ProductStats(10**9, 10**9, 10**9, 1000, 10**10, 10**6),
        ("catalyst", None): ProductStats(10**9, 10**9, 10**9, 10**10, 10**10, 10**11, 10**6),
        ("oned", None): ProductStats(10**9, 10**10, 10**9, 10**8, 10**10, 10**8),
        ("grid2d", Grid(8, 8, 1)): ProductStats(10**6, 10**6, 10**6, 10**9, 10**9, 10**12),
        ("grid3d", Grid(2, 2, 16)): ProductStats(10**9, 10**9, 10**9, 10**10, 10**10, 10**13, 10**9),
    }.items():
        assert choose_plan(stats, 64) == want
    got = {r["j"]: r["estimate"] for r in estimate_nnz_c(a, a, 64).collect()}
    want = {}
    for (_, j) in entries(catalyst(a, a)):
        want[j] = want.get(j, 0) + 1
    assert got.keys() == want.keys() and sum(got.values()) == pytest.approx(sum(want.values()), rel=0.2)


def test_partition_keys_match_spark(spark):
    keys = partition_keys(12)
    df = spark.createDataFrame([(k,) for k in keys], "x int")
    assert [r[0] for r in df.selectExpr("hash(x)").collect()] == [_murmur_int(k) for k in keys]
    assert [k % 12 for k in map(_murmur_int, keys)] == list(range(12))


def exchanges(df):
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning")


def test_plan_shapes(spark):
    a = rmat(spark, "community", 5)
    a = SparseMatrix(spark.createDataFrame(a.df.collect(), a.df.schema), a.nrows, a.ncols)
    layered = grid3d(a, a, Grid(2, 2, 2)).df
    assert exchanges(layered) == 3  # both operands to their cells, results across layers
    assert exchanges(grid2d(a, a, 2, 2).df) == 2  # results stay in their cells
    assert exchanges(oned(a, a).df) <= 3  # rows of A, who wants what, and rows of B
    text = layered._jdf.queryExecution().executedPlan().toString()
    assert "Cartesian" not in text and "BroadcastNestedLoop" not in text


def test_layouts_and_merges(spark):
    a = rmat(spark, "skewed", 5)
    d = layout.to_dcsc(a)
    assert entries(d.matrix()) == entries(layout.to_dcsc(a, 3).matrix()) == entries(a)
    assert layout.every_column(a).count() == 32 and d.df.count() == a.df.select("j").distinct().count()
    lists = merge.stage_lists(a, a, 4)
    want = sorted(map(tuple, catalyst(a, a).df.collect()))
    for f in (merge.kway_merge, merge.kway_merge_heap, merge.merge_then_reduce):
        assert sorted(map(tuple, f(lists).collect())) == want
    assert entries(kernels.column_kernel_sql(a, a)) == entries(catalyst(a, a))


def test_rmat_quadrants(spark):
    for cls, ((p, *_), degree) in CLASSES.items():
        df = rmat(spark, cls, 8).df
        n = degree << 8
        low = df.where("i < 128 AND j < 128").agg({"v": "sum"}).first()[0]
        assert abs(low - p * n) < 3 * np.sqrt(n * p * (1 - p)) and df.agg({"v": "sum"}).first()[0] == n


def test_kernels_keep_types(spark):
    from decimal import Decimal

    cells = {(i, j): ((3 * i + 5 * j) % 7 - 2) / 4 for i, j in itertools.product(range(5), range(5)) if (i + j) % 3}
    for kind, make in (("double", float), ("decimal(10,2)", lambda x: Decimal(str(x)))):
        a = SparseMatrix.rows_of(spark, [(i, j, make(v)) for (i, j), v in cells.items()], 5, 5, kind)
        want = catalyst(a, a)
        for got in (kernels.heap_kernel(a, a, Grid(2, 1, 2)), kernels.dense_acc_kernel(a, a, Grid(1, 2, 1)), kernels.column_kernel_sql(a, a), SparseMatrix(merge.kway_merge_heap(merge.stage_lists(a, a, 4), 2), 5, 5)):
            assert entries(got) == entries(want)
    b = matrix(spark, {k: int(4 * v) for k, v in cells.items()}, 5, 5)
    for s in SEMIRINGS.values():
        m = b.apply(lambda v: v > 0) if s.name == "or_and" else b
        assert entries(kernels.heap_kernel(m, m, semiring=s)) == entries(kernels.dense_acc_kernel(m, m, semiring=s)) == entries(catalyst(m, m, s)), s.name


def test_hubs_are_split(spark):
    star = {(i, 3): i + 1 for i in range(40)} | {(3, j): j + 2 for j in range(40)} | {(5, 6): 1}
    a = matrix(spark, star, 40, 40)
    hubs = heavy_inner(a, a, 8)
    assert hubs == [3]
    for h in (None, hubs):
        points = cell_points(a, a, Grid(1, 1, 2), 8, hubs=h)
        most = points.groupBy("cell").count().agg({"count": "max"}).first()[0]
        assert (most > 1500) == (h is None)
        assert entries(grid3d(a, a, Grid(1, 1, 2), threads=8, hubs=h)) == dense_product(star, star)


def test_auto_shares_hubs(spark, monkeypatch):
    star = {(i, 3): i + 1 for i in range(40)} | {(3, j): j + 2 for j in range(40)} | {(5, 6): 1}
    even = {(i, (7 * i) % 40): i + 1 for i in range(40)}
    asked = []
    monkeypatch.setattr(planner, "choose_plan", lambda s, w: ("grid3d", Grid(1, 1, 8)))
    monkeypatch.setattr(plans, "grid3d", lambda *x, **more: asked.append(more) or grid3d(*x, **more))
    for cells, hubs in ((star, [3]), (even, None)):
        a = matrix(spark, cells, 40, 40)
        assert entries(multiply(a, a)) == dense_product(cells, cells)
        assert asked[-1]["hubs"] == hubs
    most = cell_points(matrix(spark, star, 40, 40), matrix(spark, star, 40, 40), Grid(1, 1, 8), **asked[0]).groupBy("cell").count().agg({"count": "max"}).first()[0]
    assert asked[0]["threads"] >= 8 and most < 800


def test_other_plans_and_permutations(spark):
    a = rmat(spark, "skewed", 5)
    want = entries(catalyst(a, a))
    assert entries(local_sql(a, a)) == want == entries(grid3d(a, a, Grid(2, 2, 2), layout="replicate"))
    held = SparseMatrix(spark.createDataFrame(a.df.collect(), a.df.schema), a.nrows, a.ncols)
    assert exchanges(local_sql(held, held).df) == 2  # both operands, to one task
    with pytest.raises(TooMuchWork):
        local_sql(a, a, most=10)
    assert entries(multiply(a, a, plan="oned_broadcast_a")) == want
    table = digest_permutation(spark, 32)
    back = table.select("p", "x").toDF("x", "p")
    assert sorted(r["p"] for r in table.collect()) == list(range(32))
    assert entries(permute_by(catalyst(permute_by(a, table), permute_by(a, table)), back)) == want
    assert entries(power(a, 0, SEMIRINGS["plus_times"])) == {(i, i): 1 for i in range(32)}
    assert GridConfig(64, 4, 2).grid == Grid(4, 4, 4)


def test_local_product_of_large_operands_is_whole(spark):
    a = rmat(spark, "skewed", 5)
    assert entries(local_sql(a, a, most=10, beyond="rows")) == entries(catalyst(a, a))


def test_large_operands_are_not_broadcast(spark, monkeypatch):
    a = rmat(spark, "skewed", 5)
    assert "BroadcastHashJoin" in catalyst(a, a, hint="broadcast").df._jdf.queryExecution().toString()
    monkeypatch.setattr("layermul.plans.multiply.HINTED_ENTRIES", 10)
    c = catalyst(a, a, hint="broadcast")
    assert "Broadcast" not in c.df._jdf.queryExecution().toString() and entries(c) == entries(catalyst(a, a))


def test_user_semiring_folds_entries_together(spark):
    def never(x):
        raise AssertionError("called for one entry")

    a = rmat(spark, "skewed", 5)
    assert entries(catalyst(a, a, user_semiring("user", never, lambda x, y: x * y, plus=lambda x, y: x + y))) == entries(catalyst(a, a))
    for n in (0, 1, 2, 3, 7, 8, 9):
        runs = [list(range(k + 1)) for k in range(n)]
        flat = np.array([x for r in runs for x in r], np.int64)
        got = _fold_runs(flat, np.array([len(r) for r in runs], np.int64), lambda x, y: np.maximum(x, y))
        assert got.tolist() == [max(r) for r in runs]
