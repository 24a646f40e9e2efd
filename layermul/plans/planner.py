"""Cost model of the plans in messages and words, and the choice among them."""

from __future__ import annotations

from dataclasses import dataclass
from math import expm1, log2, sqrt

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from layermul.matrix import SparseMatrix

from .grid import Grid, GridConfig

#: Entries of an operand that may be sent whole to every worker (24 bytes each).
BROADCAST_ENTRIES = 400_000


@dataclass(frozen=True)
class ProductStats:
    nrows: int
    inner: int
    ncols: int
    nnz_a: int
    nnz_b: int
    flops: int
    nnz_c: int | None = None
    heaviest: int = 0  # scalar products of the inner index that has most


def measure(a: SparseMatrix, b: SparseMatrix) -> ProductStats:
    """Two grouped counts and their join on the inner index; no product is enumerated."""
    one = a.df.groupBy(F.col("j").alias("k")).agg(F.count(F.lit(1)).alias("na"))
    two = b.df.groupBy(F.col("i").alias("k")).agg(F.count(F.lit(1)).alias("nb"))
    r = one.join(two, "k", "full_outer").agg(F.sum("na").alias("a"), F.sum("nb").alias("b"), F.sum(F.col("na") * F.col("nb")).alias("f"), F.max(F.col("na") * F.col("nb")).alias("h")).first()
    return ProductStats(a.nrows, a.ncols, b.ncols, r["a"] or 0, r["b"] or 0, r["f"] or 0, heaviest=r["h"] or 0)


def broadcast_time(words: float, q: float, alpha: float, beta: float) -> float:
    return 0.0 if q <= 1 else alpha * log2(q) + beta * words * (q - 1) / q


def all_to_all_time(words: float, q: float, alpha: float, beta: float) -> float:
    return 0.0 if q <= 1 else alpha * (q - 1) + beta * words * (q - 1) / q


def comm_model(s: ProductStats, p: int, c: int, b: int, alpha: float = 1.0, beta: float = 1.0, nu: float = 1.0, mu: float = 1.0) -> float:
    """Modelled time of the layered plan with p workers in c layers and panels of width b: deal B to
    its layers, broadcast panels along rows and columns, exchange partial results across layers. nu
    and mu stretch the words for simultaneous collectives and for workers that share a node."""
    side = sqrt(p / c)
    stages = max(1.0, s.inner / (b * c))
    slow = beta * nu * mu
    panel_a, panel_b = s.nnz_a / p * side / stages, s.nnz_b / p * side / stages
    steps = stages * (broadcast_time(panel_a, side, alpha, slow) + broadcast_time(panel_b, side, alpha, slow))
    return all_to_all_time(s.nnz_b / p, c, alpha, slow) + steps + all_to_all_time(s.flops / p, c, alpha, slow)


def comm_asymptotic(s: ProductStats, p: int, c: int, b: int) -> tuple[float, float]:
    """(messages, words) per worker."""
    messages = s.inner / (b * c) * max(0.0, log2(p / c)) + c
    return messages, (s.nnz_a + s.nnz_b) / sqrt(p * c) + s.flops / p


def model_sweep(spark: SparkSession, s: ProductStats, ps: list[int], cs: list[int], bs: list[int]) -> DataFrame:
    rows = [(p, c, b, *comm_asymptotic(s, p, c, b), comm_model(s, p, c, b)) for p in ps for c in cs for b in bs if c <= p]
    told = spark.createDataFrame(rows, "p bigint, c bigint, b bigint, messages double, words double, modelled double")
    return told.select("p", "c", "b", *[F.round(x, 6).alias(x) for x in ("messages", "words", "modelled")])  # halves away from zero, as in SQL


def overlap_gain(share: float) -> float:
    """At most how many times faster if communication, `share` of the time, hides behind computation."""
    return 1 / max(share, 1 - share)


def layer_entries(s: ProductStats, layers: int) -> float:
    """Entries of all layers' results, if products fall on the result's entries evenly. Where the size
    of the result isn't known, products fall evenly on all places."""
    places = s.nnz_c if s.nnz_c is not None else -(float(s.nrows) * s.ncols) * expm1(-s.flops / max(1.0, float(s.nrows) * s.ncols))
    return 0.0 if not places else min(float(s.flops), -layers * places * expm1(-s.flops / layers / places))


def shuffle_words(s: ProductStats, grid: Grid) -> float:
    """Entries that cross a shuffle in grid3d: fanned-out operands, and partial results if there is
    more than one layer."""
    return s.nnz_a * grid.pc + s.nnz_b * grid.pr + (layer_entries(s, grid.pl) if grid.pl > 1 else 0)


def oned_words(s: ProductStats, workers: int) -> float:
    """A once to its rows' workers, its distinct inner indices by worker, and B's rows to those that want them."""
    rows = max(1.0, float(s.inner))
    wanting = -workers * expm1(-s.nnz_a / rows / workers)  # workers that want a row of B, on average
    return s.nnz_a + (rows + s.nnz_b) * wanting


def choose_plan(s: ProductStats, workers: int) -> tuple[str, Grid | None]:
    """The plan that sends the fewest entries: a small operand (its size has been counted) whole to all
    workers, else Spark's own (every partition of the inner index is a layer of one cell), rows with
    the parts of B that they want, or a grid of some number of layers."""
    if min(s.nnz_a, s.nnz_b) <= BROADCAST_ENTRIES:
        return ("oned_broadcast" if s.nnz_b <= s.nnz_a else "oned_broadcast_a"), None
    costs = {("catalyst", None): s.nnz_a + s.nnz_b + layer_entries(s, workers), ("oned", None): oned_words(s, workers)}
    layers = 1
    while layers < workers:
        g = GridConfig(workers, layers).grid
        costs["grid3d" if layers > 1 else "grid2d", g] = shuffle_words(s, g)
        layers *= 2
    return min(costs, key=costs.get)


def estimate_nnz_c(a: SparseMatrix, b: SparseMatrix, rounds: int = 16, seed: int = 42) -> DataFrame:
    """(j, estimate): size of each output column from minima of random exponential labels that travel
    from A's rows through both operands; relative error about 1 / sqrt(rounds - 2)."""
    from layermul.semiring import MIN_SECOND

    draw = lambda r: -F.log((F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(f"{seed}:{r}"), "i")), 1, 12), 16, 10).cast("double") + 0.5) / float(2**48))
    labels = a.df.select("i", F.col("j").alias("k"), *[draw(r).alias(f"l{r}") for r in range(rounds)])
    first = labels.groupBy("k").agg(*[MIN_SECOND.add(F.col(f"l{r}")).alias(f"l{r}") for r in range(rounds)])
    least = b.df.select(F.col("i").alias("k"), "j").join(first, "k").groupBy("j").agg(*[F.min(f"l{r}").alias(f"l{r}") for r in range(rounds)])
    total = sum((F.col(f"l{r}") for r in range(rounds)), F.lit(0.0))
    return least.select("j", ((rounds - 1) / total).alias("estimate"))
