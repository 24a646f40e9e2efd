"""Independent sets, restriction and coarsened matrices.

A round of mis2 gives every candidate a random priority, takes the least over closed one-hop and then
two-hop neighbourhoods, and makes members of those that hold their own least; everything within two
hops of a new member leaves. Priorities are digests of seed, round and vertex, so a lost task
computes the same ones again.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from layermul.matrix import SparseMatrix
from layermul.plans.multiply import catalyst
from layermul.plans.planner import measure
from layermul.semiring import PLUS_TIMES
from layermul.session import materialize

from .vector import mask_out, mxv, places


def md5_number(*parts: Column) -> Column:
    """The first eight hex digits of the digest of the parts joined by colons."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *[p.cast("string") for p in parts])), 1, 8), 16, 10).cast("bigint")


def closed_pattern(a: SparseMatrix) -> DataFrame:
    """(i, j) of a graph's edges in both directions and every vertex with itself."""
    own = a.df.sparkSession.range(a.nrows).select(F.col("id").alias("i"), F.col("id").alias("j"))
    return a.df.select("i", "j").unionByName(a.df.select(F.col("j").alias("i"), F.col("i").alias("j"))).unionByName(own).distinct()


def _hop(pattern: DataFrame, v: DataFrame) -> DataFrame:
    """(i, v): least value over closed neighbourhoods."""
    return pattern.join(v.select(F.col("i").alias("j"), "v"), "j").groupBy("i").agg(F.min("v").alias("v"))


def independent_set(a: SparseMatrix, seed: int = 42, hops: int = 2, redraw: bool = True, max_rounds: int = 64) -> DataFrame:
    """(i) of a maximal set whose members are more than `hops` apart. redraw: new priorities every
    round, else one draw that fixes the greedy set in its order."""
    pattern = materialize(closed_pattern(a), "pattern")
    candidates = a.df.sparkSession.range(a.nrows).select(F.col("id").alias("i"))
    members: DataFrame | None = None
    for r in range(1, max_rounds + 1):
        draw = F.md5(F.concat_ws(":", F.lit(str(seed)), F.lit(str(r if redraw else 1)), F.col("i").cast("string")))
        drawn = candidates.select("i", F.struct(draw.alias("p"), F.col("i").alias("id")).alias("v"))
        least = drawn
        for _ in range(hops):
            least = _hop(pattern, least)
        new = materialize(drawn.join(least.withColumnRenamed("v", "least"), "i").where(F.col("v") == F.col("least")).select("i"), "members")
        near = new.withColumn("v", F.lit(0))
        for _ in range(hops):
            near = _hop(pattern, near)
        members = new if members is None else members.unionByName(new)
        candidates = materialize(mask_out(candidates, near), "candidates")
        if candidates.isEmpty():
            return members
    raise RuntimeError(f"vertices left after {max_rounds} rounds")


def mis2(a: SparseMatrix, seed: int = 42, redraw: bool = True, max_rounds: int = 64) -> DataFrame:
    return independent_set(a, seed, 2, redraw, max_rounds)


def mis1(a: SparseMatrix, seed: int = 42, redraw: bool = True, max_rounds: int = 64) -> DataFrame:
    return independent_set(a, seed, 1, redraw, max_rounds)


def verify_independent_set(a: SparseMatrix, s: DataFrame, hops: int = 2) -> DataFrame:
    """One row: pairs of members within `hops`, and vertices with no member within `hops`."""
    pattern = closed_pattern(a)
    reach = s.select("i", F.col("i").alias("m"))
    for _ in range(hops):
        reach = pattern.join(reach.select(F.col("i").alias("j"), "m"), "j").select("i", "m").distinct()
    close = reach.where("i <> m").join(s, "i", "left_semi")
    bare = a.df.sparkSession.range(a.nrows).select(F.col("id").alias("i")).join(reach.select("i"), "i", "left_anti")
    return close.unionByName(bare.withColumn("m", F.lit(-1).cast("bigint"))).agg(F.count(F.lit(1)).alias("violations"))


def restriction(a: SparseMatrix, s: DataFrame, seed: int = 42, average: bool = False) -> SparseMatrix:
    """n x |S|: each member's column holds it and its neighbours; other vertices go to a column drawn
    by digest. One entry in every row, of value 1, or with average 1 / column size."""
    ranked = materialize(places(s, "i", a.nrows).select("i", F.col("upto").alias("c")), "ranked")  # one row for each aggregate
    n = ranked.count()
    pattern = closed_pattern(a)
    near = pattern.join(ranked.withColumnRenamed("i", "j"), "j").groupBy("i").agg(F.min("c").alias("c"))
    left = mask_out(a.df.sparkSession.range(a.nrows).select(F.col("id").alias("i")), near)
    drawn = left.select("i", F.pmod(md5_number(F.lit(str(seed)), F.lit("left"), F.col("i")), F.lit(max(n, 1)).cast("bigint")).alias("c"))
    r = SparseMatrix(near.unionByName(drawn).select("i", F.col("c").alias("j"), F.lit(1).cast("bigint").alias("v")), a.nrows, n)
    if average:
        size = r.df.groupBy("j").agg(F.count(F.lit(1)).alias("size"))
        r = r.with_df(r.df.join(size, "j").select("i", "j", (1.0 / F.col("size")).alias("v")))
    return r


def verify_restriction(r: SparseMatrix) -> DataFrame:
    """One row: vertices without exactly one entry, and empty columns."""
    rows = r.df.sparkSession.range(r.nrows).select(F.col("id").alias("i")).join(r.df, "i", "left").groupBy("i").agg(F.count("v").alias("n")).where("n <> 1").agg(F.count(F.lit(1)).alias("x"))
    cols = r.df.sparkSession.range(r.ncols).select(F.col("id").alias("j")).join(r.df.select("j"), "j", "left_anti").agg(F.count(F.lit(1)).alias("y"))
    return rows.join(cols).select((F.col("x") + F.col("y")).alias("violations"))


def restrict_left(a: SparseMatrix, r: SparseMatrix, product=catalyst) -> SparseMatrix:
    return product(r.t, a)


def restrict_right(a: SparseMatrix, r: SparseMatrix, product=catalyst) -> SparseMatrix:
    return product(a, r)


def galerkin(a: SparseMatrix, r: SparseMatrix, order: str = "left", product=catalyst) -> SparseMatrix:
    """RᵀA R in two products: (RᵀA) R with order left, Rᵀ (A R) with right, the cheaper first product
    with auto."""
    if order == "auto":
        order = "left" if measure(r.t, a).flops <= measure(a, r).flops else "right"
    return product(product(r.t, a), r) if order == "left" else product(r.t, product(a, r))


def contract(a: SparseMatrix, labels: DataFrame, n: int) -> SparseMatrix:
    """The same for one entry of value 1 a row: relabel both indices by labels (i, c) and sum."""
    one = a.df.join(labels.select("i", F.col("c").alias("ci")), "i")
    two = one.join(labels.select(F.col("i").alias("j"), F.col("c").alias("cj")), "j")
    return SparseMatrix(two.groupBy(F.col("ci").alias("i"), F.col("cj").alias("j")).agg(F.sum("v").alias("v")), n, n)


def hierarchy(a: SparseMatrix, smallest: int = 50, levels: int = 10, seed: int = 42) -> list[tuple[SparseMatrix, SparseMatrix | None]]:
    """(A, R) of each level until the coarse matrix has at most `smallest` rows; the last has no R."""
    out = []
    for _ in range(levels):
        if a.nrows <= smallest:
            break
        r = restriction(a, mis2(a, seed), seed)
        r = r.with_df(materialize(r.df, "restriction"))
        if r.ncols >= a.nrows:
            break
        out.append((a, r))
        coarse = galerkin(a, r, "auto")
        a = SparseMatrix(materialize(coarse.df, "coarse"), r.ncols, r.ncols)
    return [*out, (a, None)]


def restrict_vector(r: SparseMatrix, x: DataFrame) -> DataFrame:
    """(i, v) on the coarse vertices: Rᵀ x."""
    return mxv(r.t, x, PLUS_TIMES)


def prolong_vector(r: SparseMatrix, x: DataFrame) -> DataFrame:
    """(i, v) on the fine vertices: R x."""
    return mxv(r, x, PLUS_TIMES)


def residual(a: SparseMatrix, x: DataFrame, b: DataFrame) -> DataFrame:
    """(i, v) of b - A x, with entries wherever either has one."""
    both = b.select("i", "v").unionByName(mxv(a, x, PLUS_TIMES).select("i", (-F.col("v")).alias("v")))
    return both.groupBy("i").agg(F.sum("v").alias("v"))
