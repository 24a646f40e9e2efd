"""Runners of the experiment workloads: rows (workload, matrix, plan, pr, pc, pl, cores, phase,
metric, value). Counts are exact; times are of the machine they run on."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from layermul.matrix import SparseMatrix
from layermul.operators import coarsen, cost, kernels, merge
from layermul.plans.grid import Grid, GridConfig
from layermul.plans.multiply import catalyst, cell_points, grid2d, grid3d, layer_results, local_sql, oned
from layermul.plans.planner import comm_asymptotic, measure
from layermul.session import configure, materialize
from layermul.sources.datasets import mesh_part
from layermul.sources.generators import rmat, rmat_pair

SessionOf = Callable[[int], SparkSession]


def _row(workload: str, matrix: str, plan: str, grid: Grid = Grid(), cores: int = 0, phase: str = "all", metric: str = "seconds", value: float = 0.0) -> dict:
    return {"workload": workload, "matrix": matrix, "plan": plan, "pr": grid.pr, "pc": grid.pc, "pl": grid.pl, "cores": cores, "phase": phase, "metric": metric, "value": round(float(value), 4)}


def _seconds(df: DataFrame) -> float:
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def _held(m: SparseMatrix) -> SparseMatrix:
    return m.with_df(materialize(m.df, "held"))


def run_plans(a: SparseMatrix, b: SparseMatrix, grids: list[Grid], name: str, workload: str) -> Iterator[dict]:
    """Seconds of every plan on one product, and what each grid moves and holds."""
    plans = {"catalyst": lambda: catalyst(a, b), "oned": lambda: oned(a, b), "oned_broadcast": lambda: oned(a, b, broadcast=True), "grid2d": lambda: grid2d(a, b, 2, 2)}
    for plan, make in plans.items():
        yield _row(workload, name, plan, value=_seconds(make().df))
    for g in grids:
        yield _row(workload, name, "grid3d", g, value=_seconds(grid3d(a, b, g).df))
        for r in cost.words_moved(a, b, g).collect():
            yield _row(workload, name, "grid3d", g, phase=r["phase"], metric="words", value=r["total"])
        m = cost.memory_factor(a, b, g).first()
        yield _row(workload, name, "grid3d", g, metric="memory_factor", value=m["nnz_int"] / max(1, m["nnz_c"]))
        w = cost.imbalance(a, b, g).first()
        yield _row(workload, name, "grid3d", g, metric="imbalance", value=w["max_flops"] * w["cells"] / max(1, w["flops"]))


def run_square(a: SparseMatrix, grids: list[Grid], name: str) -> Iterator[dict]:
    yield from run_plans(a, a, grids, name, "square")


def run_pair(spark: SparkSession, cls: str, scale: int, grids: list[Grid], seeds: tuple[int, int] = (42, 43)) -> Iterator[dict]:
    a, b = (_held(m) for m in rmat_pair(spark, cls, scale, seeds))
    yield from run_plans(a, b, grids, f"{cls}{scale}", "pair")


def run_restriction(a: SparseMatrix, name: str, side: str = "left") -> Iterator[dict]:
    r = _held(coarsen.restriction(a, coarsen.mis2(a)))
    one, two = (r.t, a) if side == "left" else (a, r)
    yield from run_plans(one, two, [Grid(4, 4, 1), Grid(2, 2, 4)], name, "RtA" if side == "left" else "AR")


def run_galerkin(a: SparseMatrix, name: str) -> Iterator[dict]:
    r = _held(coarsen.restriction(a, coarsen.mis2(a)))
    for order in ("left", "right"):
        yield _row("RtAR", name, order, value=_seconds(coarsen.galerkin(a, r, order).df))
    yield _row("RtAR", name, "contract", value=_seconds(coarsen.contract(a, r.df.select("i", F.col("j").alias("c")), r.ncols).df))


def run_library_comparison(a: SparseMatrix, name: str) -> Iterator[dict]:
    """A R by the one-dimensional plan with randomly dealt rows, against the grids."""
    r = _held(coarsen.restriction(a, coarsen.mis2(a)))
    for plan, make in {"oned": lambda: oned(a, r), "grid2d": lambda: grid2d(a, r, 4, 4), "grid3d": lambda: grid3d(a, r, Grid(2, 2, 4))}.items():
        yield _row("AR", name, plan, value=_seconds(make().df))


def run_permutation_ablation(a: SparseMatrix, name: str, grid: Grid = Grid(4, 4, 1)) -> Iterator[dict]:
    from layermul.matrix import AffinePermutation

    for kind, m in (("given", a), ("permuted", a.permute(AffinePermutation.near(a.nrows)))):
        w = cost.imbalance(m, m, grid).first()
        yield _row("permutation", name, kind, grid, metric="imbalance", value=w["max_flops"] * w["cells"] / max(1, w["flops"]))


def strong_scaling(session: SessionOf, sf_dir: str, cores: list[int]) -> Iterator[dict]:
    """One product on 1, 2, 4 ... cores, and the summary of speed-ups over matrices."""
    took: dict[str, list[float]] = {}
    for c in cores:
        spark = configure(session(c))
        for name, m in {"mesh": mesh_part(spark, sf_dir), "skewed12": rmat(spark, "skewed", 12)}.items():
            m = _held(m)
            _seconds(grid3d(m, m, Grid(2, 2, 2)).df)
            took.setdefault(name, []).append(s := _seconds(grid3d(m, m, Grid(2, 2, 2)).df))
            yield _row("strong_scaling", name, "grid3d", Grid(2, 2, 2), c, value=s)
        spark.stop()
    ups = [t[0] / t[-1] for t in took.values()]
    mean = sum(ups) / len(ups)
    for metric, v in (("mean", mean), ("min", min(ups)), ("max", max(ups)), ("stddev", (sum((u - mean) ** 2 for u in ups) / len(ups)) ** 0.5)):
        yield _row("strong_scaling", "all", "grid3d", Grid(2, 2, 2), cores[-1], metric=f"speedup_{metric}", value=v)


def ct_sweep(session: SessionOf, sf_dir: str, cpus: int) -> Iterator[dict]:
    """Layers against cells, and processes against their threads, at 16 workers in all."""
    spark = configure(session(cpus))
    for name, m in {"skewed12": rmat(spark, "skewed", 12), "mesh": mesh_part(spark, sf_dir)}.items():
        m = _held(m)
        yield from run_square(m, [Grid(4, 4, 1), Grid(2, 2, 4), Grid(1, 1, 16)], name)
        for layers, threads in ((1, 1), (1, 4), (4, 1), (4, 4), (16, 1)):
            g = GridConfig(max(layers, 16 // threads), layers, threads)
            yield _row("ct", name, f"grid3d,t={threads}", g.grid, cpus, value=_seconds(grid3d(m, m, g.grid, threads=threads).df))
    spark.stop()


def kernel_scaling(session: SessionOf, sf_dir: str, cores: list[int]) -> Iterator[dict]:
    """The kernels by threads, a skewed matrix and a mesh, against the routine in one task."""
    for c in cores:
        spark = configure(session(c))
        for name, m in {"skewed10": rmat(spark, "skewed", 10), "mesh": mesh_part(spark, sf_dir)}.items():
            m = _held(m)
            plans = {"heap": lambda: kernels.heap_kernel(m, m, parts=c), "dense_acc": lambda: kernels.dense_acc_kernel(m, m, parts=c), "column_sql": lambda: kernels.column_kernel_sql(m, m), "local_sql": lambda: local_sql(m, m)}  # noqa: B023
            for plan, make in plans.items():
                yield _row("kernel", name, plan, cores=c, value=_seconds(make().df))
        spark.stop()


def merge_scaling(session: SessionOf, sf_dir: str, cores: list[int]) -> Iterator[dict]:
    """The stage lists of one cell of a 4 x 4 and of a 16 x 16 grid, merged three ways."""
    for c in cores:
        spark = configure(session(c))
        m = _held(rmat(spark, "skewed", 12))
        for k in (4, 16):
            lists = materialize(merge.cell_stage_lists(m, m, Grid(k, k, 1)), "lists")
            ways = {"kway": merge.kway_merge, "kway_heap": lambda x: merge.kway_merge_heap(x, c), "merge_then_reduce": merge.merge_then_reduce}  # noqa: B023
            for plan, f in ways.items():
                yield _row("merge", f"skewed12/{k}", plan, cores=c, value=_seconds(f(lists)))
        spark.stop()


def breakdown(session: SessionOf, sf_dir: str, cpus: int) -> Iterator[dict]:
    """Phases written down one by one, with the entries that each moves or makes: operands to their cells,
    the join inside cells, combining there, and across layers."""
    spark = configure(session(cpus))
    m = _held(rmat(spark, "skewed", 12))
    for g in (Grid(4, 4, 1), Grid(2, 2, 4), Grid(1, 1, 16)):
        words = {r["phase"]: r["total"] for r in cost.words_moved(m, m, g).collect()}
        for phase, n in words.items():
            yield _row("breakdown", "skewed12", "grid3d", g, cpus, phase, "words", n)
        joined = _seconds(cell_points(m, m, g).agg(F.count(F.lit(1))))
        yield _row("breakdown", "skewed12", "grid3d", g, cpus, "broadcast_and_join", value=joined)
        began = time.perf_counter()
        part = materialize(layer_results(m, m, g), "partial")
        yield _row("breakdown", "skewed12", "grid3d", g, cpus, "local_multiply_and_layer_merge", value=max(0.0, time.perf_counter() - began - joined))
        yield _row("breakdown", "skewed12", "grid3d", g, cpus, "all_to_all_and_fiber_merge", value=_seconds(merge.kway_merge(part)) if g.pl > 1 else 0.0)
    spark.stop()


def model_against_counts(session: SessionOf, sf_dir: str, cpus: int) -> Iterator[dict]:
    """Words that the model gives from measured sizes, beside the words that are counted."""
    spark = configure(session(cpus))
    for name, m in {"skewed12": rmat(spark, "skewed", 12), "mesh": mesh_part(spark, sf_dir)}.items():
        m = _held(m)
        stats = measure(m, m)
        for g in (Grid(4, 4, 1), Grid(2, 2, 4), Grid(1, 1, 16)):
            counted = sum(r["total"] for r in cost.words_moved(m, m, g).collect())
            yield _row("model", name, "grid3d", g, cpus, metric="words_counted", value=counted)
            yield _row("model", name, "grid3d", g, cpus, metric="words_modelled", value=g.cells * comm_asymptotic(stats, g.cells, g.pl, 64)[1])
    spark.stop()
