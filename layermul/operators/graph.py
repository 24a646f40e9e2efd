"""Graph functions as products over semirings."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from layermul.matrix import SparseMatrix
from layermul.plans.multiply import catalyst, multiply
from layermul.semiring import MAX_MIN, MIN_PLUS, OR_AND, PLUS_PAIR, Semiring
from layermul.session import materialize


def triangles(a: SparseMatrix) -> DataFrame:
    """One row: triangles of a graph whose pattern is symmetric, as (L L) masked by L."""
    low = a.pattern().tril()
    return multiply(low, low, PLUS_PAIR, "catalyst", mask=low).df.agg(F.coalesce(F.sum("v"), F.lit(0)).cast("bigint").alias("triangles"))


#: What leaves a value as it is when multiplied.
_ONES = {"plus_times": 1, "max_times": 1, "min_plus": 0, "or_and": True}


def power(a: SparseMatrix, k: int, semiring: Semiring) -> SparseMatrix:
    """a to the k over a semiring, by squaring; to the 0 the semiring's identity, where it has one."""
    if k == 0:
        if semiring.name not in _ONES:
            raise ValueError(f"{semiring.name} has no identity here")
        return SparseMatrix.eye(a.df.sparkSession, a.nrows).apply(lambda v: F.lit(_ONES[semiring.name]).cast(a.df.schema["v"].dataType))
    out, base = None, a
    while k:
        if k & 1:
            out = base if out is None else catalyst(out, base, semiring)
        k >>= 1
        if k:
            base = base.with_df(materialize(catalyst(base, base, semiring).df, "power"))
    return out


def khop_costs(a: SparseMatrix, k: int) -> SparseMatrix:
    return power(a, k, MIN_PLUS)


def widest_paths(a: SparseMatrix, k: int) -> SparseMatrix:
    return power(a, k, MAX_MIN)


def reachable(a: SparseMatrix, k: int) -> SparseMatrix:
    return power(a.apply(lambda v: F.lit(True)), k, OR_AND)


def cycle_lengths(a: SparseMatrix, k: int) -> DataFrame:
    """(length, vertices) for lengths 1 to k: on how many vertices closed walks of that length start."""
    one = a.off_diagonal().apply(lambda v: F.lit(True))
    out, walk = None, one
    for n in range(1, k + 1):
        if n > 1:
            walk = one.with_df(materialize(catalyst(walk, one, OR_AND).df, "walk"))
        row = walk.diagonal().df.agg(F.lit(n).cast("bigint").alias("length"), F.count(F.lit(1)).alias("vertices"))
        out = row if out is None else out.unionByName(row)
    return out


def has_cycle(a: SparseMatrix, k: int) -> bool:
    return cycle_lengths(a, k).where("vertices > 0").limit(1).count() > 0


def peer_pressure(a: SparseMatrix, labels: DataFrame | None = None, rounds: int = 1) -> DataFrame:
    """(i, v): each vertex takes the label that most of its neighbours (and itself) have, the least of
    those with as many votes."""
    own = a.df.sparkSession.range(a.nrows).select(F.col("id").alias("i"), F.col("id").alias("v"))
    labels = own if labels is None else labels
    closed = a.df.select("i", "j").unionByName(own.toDF("i", "j")).distinct()
    for _ in range(rounds):
        votes = closed.join(labels.select(F.col("i").alias("j"), "v"), "j").groupBy("i", "v").agg(F.count(F.lit(1)).alias("n"))
        labels = votes.groupBy("i").agg(F.max_by("v", F.struct("n", -F.col("v"))).alias("v"))
        labels = materialize(labels, "labels") if rounds > 1 else labels
    return labels


def flow_step(a: SparseMatrix, inflation: float = 2.0, least: float = 1e-4) -> SparseMatrix:
    """One step of flow clustering: columns normalised, squared, raised to a power, small ones
    dropped, normalised."""

    def normal(m: SparseMatrix) -> SparseMatrix:
        s = m.df.groupBy("j").agg(F.sum("v").alias("s"))
        return m.with_df(m.df.join(s, "j").select("i", "j", (F.col("v") / F.col("s")).alias("v")))

    m = normal(a.apply(lambda v: v.cast("double")))
    return normal(catalyst(m, m).apply(lambda v: F.pow(v, F.lit(inflation))).where(F.col("v") >= least))


def flow_clusters(a: SparseMatrix, inflation: float = 2.0, least: float = 1e-4, rounds: int = 10) -> DataFrame:
    """(i, c): for every vertex the attractor that draws most of its flow after `rounds` steps on the
    closed graph."""
    m = a.pattern().ewise_add(SparseMatrix.eye(a.df.sparkSession, a.nrows), F.greatest)
    for _ in range(rounds):
        m = m.with_df(materialize(flow_step(m, inflation, least).df, "flow"))
    return m.df.groupBy(F.col("j").alias("i")).agg(F.max_by("i", F.struct("v", -F.col("i"))).alias("c"))


def betweenness_level(a: SparseMatrix, frontier: SparseMatrix, seen: SparseMatrix) -> SparseMatrix:
    """The next level of a batch of searches: path counts of vertices not seen (source x vertex)."""
    return multiply(frontier, a.pattern(), plan="catalyst").mask(seen, complement=True)


def betweenness(a: SparseMatrix, sources: list[int], longest: int | None = None) -> DataFrame:
    """(i, v): each vertex's share of shortest paths from the sources, by levels forward and back.
    With `longest`, longer paths raise ValueError."""
    spark = a.df.sparkSession
    front = SparseMatrix.rows_of(spark, [(s, v, 1) for s, v in enumerate(sources)], len(sources), a.nrows)
    levels, seen = [front], front
    while True:
        nxt = betweenness_level(a, levels[-1], seen)
        nxt = nxt.with_df(materialize(nxt.df, "level"))
        if nxt.df.isEmpty():
            break
        if longest is not None and len(levels) > longest:
            raise ValueError(f"paths of more than {longest} edges")
        levels.append(nxt)
        seen = seen.with_df(materialize(seen.df.unionByName(nxt.df), "seen"))
    edges = a.df.select(F.col("i").alias("from"), F.col("j").alias("to"))
    delta = None
    for upper, lower in zip(levels[-2::-1], levels[:0:-1], strict=True):
        paths = lower.df.toDF("s", "to", "paths")
        part = paths.withColumn("d", F.lit(0.0)) if delta is None else paths.join(delta.toDF("s", "to", "d"), ["s", "to"], "left").fillna(0.0, ["d"])
        back = part.join(edges, "to").join(upper.df.toDF("s", "from", "own"), ["s", "from"])
        level = back.groupBy("s", "from").agg(F.sum(F.col("own") / F.col("paths") * (1 + F.col("d"))).alias("d"))
        level = materialize(level, "delta")
        delta = level if delta is None else delta.unionByName(level.toDF(*delta.columns))
    if delta is None:
        return spark.createDataFrame([], "i bigint, v double")
    starts = front.df.toDF("s", "from", "one").drop("one")
    return delta.join(starts, ["s", "from"], "left_anti").groupBy(F.col("from").alias("i")).agg(F.sum("d").alias("v"))


def schur_diagonal(a: SparseMatrix, split: int) -> SparseMatrix:
    """D - C inv(B) B' where the leading `split` rows and columns form a diagonal block B without zeros."""
    n = a.nrows
    b = a.extract((0, split), (0, split)).diagonal().df.select(F.col("i").alias("k"), F.col("v").alias("p"))
    right = a.extract((0, split), (split, n))
    scaled = SparseMatrix(right.df.withColumnRenamed("i", "k").join(b, "k").select(F.col("k").alias("i"), "j", (F.col("v") / F.col("p")).alias("v")), split, n - split)
    d = a.extract((split, n), (split, n)).apply(lambda v: v.cast("double"))
    return d.subtract(catalyst(a.extract((split, n), (0, split)), scaled))
