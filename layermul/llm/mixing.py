"""Mixing sources to target weights by Pareto order sampling.

Sources share all words by weight; a target stops at `cap` times its source's words and the excess
is reshared by weight. Within a source the expected number of copies grows with a document's size:
it is a level of the source times lean + floor(log2 size), `cap` at most, and the level is such that
the expected words are the target. The whole part of that number is allocated to all documents for
certain; the fractional part is the document's inclusion probability for one copy more. Documents
are ranked by random odds divided by inclusion odds, which differ between size classes, and taken in
that order until the source's remaining words are used up. Further passes fill what a long document
at the border left open, where that is more than `near` of the target; they favour short documents,
by no more words than that document has.

Which documents a pass takes depends on the document's own rank and size and on a few numbers per
source (cut and gap) and size class, so the choice is one map over the documents. The cuts come from
sums over rank buckets, about the square root of the source's documents in number, and the rows of
the one border bucket: no source is ever gathered in one task.

Edge cases: a null or empty text has size 0, is taken never and leaves its source's target alone;
a null source is a source of its own, after all others; documents equal in id and text are taken
together; an empty table gives an empty result; extra columns are kept, but for those with the names
of the result's own.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .scratch import broadcast_if_small, counted, discard, materialize, table


@dataclass(frozen=True)
class MixConfig:
    """weights: repeated over the sources in code point order; cap: most copies of a document; lean:
    the smaller, the more a long document is preferred; passes: how often a gap is filled; near: share
    of a target that may stay open; seed: of the random odds."""

    weights: tuple[int, ...] = (1, 2, 3)
    cap: int = 3
    lean: int = 8
    passes: int = 3
    near: float = 0.01
    seed: int = 42


def _size_and_draw(config: MixConfig) -> tuple[Column, Column]:
    text = F.coalesce("text", F.lit(""))
    digest = F.md5(F.concat_ws(":", F.lit(str(config.seed)), F.coalesce(F.col("doc_id").cast("string"), F.lit("")), text))
    size = F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")).cast("long")
    return size, (F.conv(F.substring(digest, 1, 12), 16, 10).cast("double") + 0.5) / float(2**48)


def sized(docs: DataFrame, config: MixConfig) -> DataFrame:
    """doc_id, source, size and u, uniform in (0, 1) from id and text: equal on every run."""
    size, u = _size_and_draw(config)
    return docs.select("doc_id", "source", size.alias("size"), u.alias("u"))


def targets(rows: DataFrame, config: MixConfig) -> DataFrame:
    """One row per source: source, source_size, n_docs, target. A row count in the number of sources."""
    per = rows.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("n_docs"))
    place = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    per = per.withColumn("weight", F.element_at(F.array(*[F.lit(float(w)) for w in config.weights]), (place % len(config.weights) + 1).cast("int")))
    # water level: sources in order of limit / weight; the first k are at their limit, the others at level * weight
    ratio = F.col("source_size") * config.cap / F.col("weight")
    before = Window.orderBy("ratio", F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    every = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    level = (F.sum("source_size").over(every) - F.coalesce(F.sum(F.col("source_size") * config.cap).over(before), F.lit(0))) / (F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
    per = per.withColumn("ratio", ratio).withColumn("level", level).withColumn("turn", F.row_number().over(Window.orderBy("ratio", F.col("source").asc_nulls_last())))
    fits = F.when(F.col("level") <= F.col("ratio"), F.struct("turn", "level"))
    per = per.withColumn("cut", F.min(fits).over(every))  # the first source that stays below its limit sets the level
    limit = (F.col("source_size") * config.cap).cast("double")
    return per.select("source", "source_size", "n_docs", F.when(F.col("turn") < F.col("cut.turn"), limit).otherwise(F.least(F.col("cut.level") * F.col("weight"), limit)).alias("target"))


def size_class(size: Column) -> Column:
    """floor(log2 size), exactly; -1 for size 0."""
    return F.when(size > 0, F.length(F.bin(size)) - 1).otherwise(-1).cast("int")


def class_shares(rows: DataFrame, config: MixConfig) -> DataFrame:
    """One row per source and size class: source, class, source_size, n_docs, target, whole, share and
    words. A row count in the number of sources, times some twenty."""
    t = targets(rows, config)
    per = rows.groupBy("source", size_class(F.col("size")).alias("class")).agg(F.sum("size").alias("words"))
    per = per.alias("c").join(t.alias("t"), F.col("c.source").eqNullSafe(F.col("t.source"))).select("c.source", "class", "words", "source_size", "n_docs", "target", F.expr(f"if(class < 0, 0, class + {config.lean})").alias("odds"))
    # classes from the largest: the first k are at the cap, the others at level * odds
    order = Window.partitionBy("source").orderBy(F.desc("class"))
    before, rest = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(0, Window.unboundedFollowing)
    weighed = F.sum(F.col("words") * F.col("odds")).over(rest)
    level = F.when(weighed > 0, (F.col("target") - F.coalesce(F.sum("words").over(before), F.lit(0)) * config.cap) / weighed)
    per = per.withColumn("level", level).withColumn("fits", F.when(F.col("level") * F.col("odds") <= config.cap, F.struct((-F.col("class")).alias("turn"), "level")))
    per = per.withColumn("cut", F.min("fits").over(Window.partitionBy("source")))
    copies = F.when(F.col("class") < 0, 0.0).when(F.col("cut").isNull() | (-F.col("class") < F.col("cut.turn")), float(config.cap)).otherwise(F.col("cut.level") * F.col("odds"))
    per = per.withColumn("copies", F.when(copies >= config.cap - 1e-9, float(config.cap)).otherwise(copies))
    return per.select("source", "class", "words", "source_size", "n_docs", "target", F.floor("copies").alias("whole"), (F.col("copies") - F.floor("copies")).alias("share"))


def _rank(u: Column, p: Column) -> Column:
    """Random odds over inclusion odds, mapped into (0, 1) without changing the order."""
    key = (u / (1 - u)) * ((1 - p) / p)
    return key / (1 + key)


def _chosen(config: MixConfig, passes: int) -> Column:
    """Which pass takes the row, as a condition on r, size and the source's cuts and gaps."""
    taken = F.lit(False)
    for k in range(passes):
        taken = taken | ((F.col("size") <= F.col(f"gap{k}")) & (F.col("r") <= F.col(f"cut{k}")))
    return taken & (F.col("size") > 0)


def _same(x: str, y: str, *names: str) -> Column:
    out = F.lit(True)
    for n in names:
        out = out & F.col(f"{x}.{n}").eqNullSafe(F.col(f"{y}.{n}"))
    return out


def mix_plan(rows: DataFrame, config: MixConfig = MixConfig()) -> DataFrame:
    """Per source and size class: source_size, target, whole copies, share (inclusion probability of one
    more), and the source's cut and gap of every pass. rows comes from sized(), written down."""
    shares, n_shares = counted(class_shares(rows, config), "mix-shares")
    gaps = shares.groupBy("source").agg(F.first("target").alias("target"), (F.first("target") - F.sum(F.col("whole") * F.col("words"))).alias("gap0"))
    ranked = (
        rows.alias("d").join(broadcast_if_small(shares.where("share > 0"), n_shares).alias("s"), _same("d", "s", "source") & (size_class(F.col("d.size")) == F.col("s.class")))
        .select("d.source", "size", _rank(F.col("u"), F.col("share")).alias("r"), F.ceil(F.sqrt("n_docs")).alias("buckets"))
    )
    done = []
    for k in range(config.passes):
        gaps, n = counted(gaps, f"mix-gaps{k}")
        done.append(gaps)
        open_rows = (
            ranked.alias("d").join(broadcast_if_small(gaps, n).alias("p"), _same("d", "p", "source"))
            .where((F.col("size") <= F.col(f"gap{k}")) & ~_chosen(config, k))
            .select("d.source", "size", "r", F.floor(F.col("r") * F.col("buckets")).alias("bucket"))
        )
        sums = materialize(open_rows.groupBy("source", "bucket").agg(F.sum("size").alias("words")), f"mix-buckets{k}")
        upto = Window.partitionBy("source").orderBy("bucket")
        cum = sums.withColumn("upto", F.sum("words").over(upto)).alias("c").join(gaps.select("source", f"gap{k}").alias("p"), _same("c", "p", "source"))
        over = cum.select("c.source", "bucket", "words", "upto", (F.col("upto") > F.col(f"gap{k}")).alias("over"), f"gap{k}")
        border = over.where("over").groupBy("source", f"gap{k}").agg(F.min("bucket").alias("bucket"), F.min(F.col("upto") - F.col("words")).alias("before"))
        inside = (
            open_rows.alias("o").join(broadcast_if_small(border, n).alias("b"), _same("o", "b", "source", "bucket"))
            .select("o.source", "r", "size", "before", f"gap{k}")
            .groupBy("source", "r", "before", f"gap{k}").agg(F.sum("size").alias("words"))
            .withColumn("upto", F.col("before") + F.sum("words").over(Window.partitionBy("source").orderBy("r")))
        )
        last = inside.groupBy("source").agg(
            F.max(F.when(F.col("upto") <= F.col(f"gap{k}"), F.col("r"))).alias("fits"), F.max(F.when(F.col("upto") <= F.col(f"gap{k}"), F.col("upto"))).alias("used"),
            F.min("r").alias("first"), F.min("before").alias("before"))
        whole = sums.groupBy("source").agg(F.sum("words").alias("all_words"))
        cuts = whole.alias("w").join(last.alias("l"), _same("w", "l", "source"), "left").select(
            "w.source", F.when(F.col("first").isNull(), 1.0).otherwise(F.col("fits")).alias("fits"),
            "first", F.when(F.col("first").isNull(), F.col("all_words")).otherwise(F.coalesce("used", "before")).alias("used"))
        left = F.col(f"gap{k}") - F.coalesce("used", F.lit(0))
        gaps = gaps.alias("p").join(cuts.alias("c"), _same("p", "c", "source"), "left").select(
            "p.*",
            # no row of the border bucket fits: the cut lies just below the bucket's first row
            F.coalesce("fits", F.col("first") - 2.0**-53, F.lit(-1.0)).alias(f"cut{k}"),
            F.when(left > config.near * F.col("target"), left).otherwise(0.0).alias(f"gap{k + 1}"),
        )
        done.append(sums)
    numbers = [f"{c}{k}" for k in range(config.passes) for c in ("cut", "gap")]
    plan = materialize(shares.alias("s").join(gaps.alias("g"), _same("s", "g", "source")).select("s.source", "class", "source_size", "s.target", "whole", "share", *numbers), "mix-plan")
    discard(shares, *done)
    return plan


#: Columns that mix() adds; they take the place of columns of the same names.
ADDED = ("size", "source_size", "target", "copies")


def mix(rows: DataFrame, plan: DataFrame, config: MixConfig = MixConfig()) -> DataFrame:
    """All columns of rows (which hold source, size and u) but u, and ADDED."""
    held = [c for c in rows.columns if c != "u" and c not in ADDED]
    packed = rows.select(F.struct(*held).alias("row"), "source", "size", "u").alias("d")
    joined = packed.join(broadcast_if_small(plan, plan.count()).alias("p"), _same("d", "p", "source") & (size_class(F.col("size")) == F.col("class")))
    joined = joined.withColumn("r", F.when(F.col("share") > 0, _rank(F.col("u"), F.col("share"))).otherwise(2.0))
    copies = F.when(F.col("size") > 0, F.col("whole") + _chosen(config, config.passes).cast("long")).otherwise(F.lit(0)).cast("long")
    return joined.select("row", "size", "source_size", "target", copies.alias("copies")).select("row.*", *ADDED)


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    config = MixConfig()
    rows = materialize(sized(table(spark, sf_dir, "documents"), config), "mix-rows")
    mixed = mix(rows, mix_plan(rows, config), config)
    return mixed.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


def mixed_documents(docs: DataFrame, config: MixConfig = MixConfig()) -> DataFrame:
    """docs with each row repeated as often as the mix takes it, in docs' own columns."""
    rows = materialize(sized(docs, config), "mix-rows")
    plan = mix_plan(rows, config)
    size, u = _size_and_draw(config)
    full = mix(docs.select(F.struct(*docs.columns).alias("row"), "source", size.alias("size"), u.alias("u")), plan, config)
    return full.where(F.col("copies") > 0).select("row", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))).select("row.*")


def op5_oracle(config: MixConfig = MixConfig()) -> str:
    """The same mixture by running sums over whole sources, for small tables."""
    weights = f"[{', '.join(f'{float(w)}::DOUBLE' for w in config.weights)}]"
    steps = []
    for k in range(config.passes):
        free = " AND ".join(["size > 0", "share > 0", f"size <= gap{k}", *[f"NOT taken{i}" for i in range(k)]])
        steps.append(f"""o{k} AS (SELECT *, coalesce(sum(CASE WHEN {free} THEN size END) OVER (PARTITION BY source ORDER BY CASE WHEN {free} THEN r ELSE 9 END RANGE UNBOUNDED PRECEDING), 0) AS upto{k}, {free} AS open{k} FROM {f"g{k - 1}" if k else "g"}),
          t{k} AS (SELECT *, open{k} AND upto{k} <= gap{k} AS taken{k} FROM o{k}),
          l{k} AS (SELECT *, gap{k} - coalesce(max(CASE WHEN taken{k} THEN upto{k} END) OVER (PARTITION BY source), 0) AS left{k} FROM t{k}),
          g{k} AS (SELECT *, CASE WHEN left{k} > {config.near}::DOUBLE * target THEN left{k} ELSE 0 END AS gap{k + 1} FROM l{k})""")
    taken = " OR ".join(f"taken{k}" for k in range(config.passes))
    return rf"""WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
          (('0x' || substr(md5('{config.seed}:' || coalesce(doc_id::VARCHAR, '') || ':' || coalesce(text, '')), 1, 12))::BIGINT + 0.5::DOUBLE) / {2**48}::DOUBLE AS u FROM documents),
      s AS (SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS place FROM d GROUP BY source),
      w AS (SELECT *, {weights}[place % {len(config.weights)} + 1] AS weight FROM s),
      l AS (SELECT *, source_size * {config.cap} / weight AS ratio, row_number() OVER (ORDER BY source_size * {config.cap} / weight, source NULLS LAST) AS turn FROM w),
      v AS (SELECT *, (sum(source_size) OVER () - coalesce(sum(source_size * {config.cap}) OVER (ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::DOUBLE
          / (sum(weight) OVER () - coalesce(sum(weight) OVER (ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) AS level FROM l),
      c AS (SELECT turn AS cut_turn, level AS cut_level FROM v WHERE level <= ratio ORDER BY turn LIMIT 1),
      p AS (SELECT source, source_size, CASE WHEN turn < cut_turn THEN (source_size * {config.cap})::DOUBLE ELSE least(cut_level * weight, (source_size * {config.cap})::DOUBLE) END AS target FROM v, c),
      e AS (SELECT *, CASE WHEN size > 0 THEN length(bin(size)) - 1 ELSE -1 END AS class FROM d),
      k AS (SELECT source, class, sum(size)::BIGINT AS words, CASE WHEN class < 0 THEN 0 ELSE class + {config.lean} END AS odds FROM e GROUP BY source, class),
      h AS (SELECT k.*, source_size, target, coalesce(sum(words) OVER (PARTITION BY k.source ORDER BY class DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before,
          sum(words * odds) OVER (PARTITION BY k.source ORDER BY class DESC ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS weighed FROM k JOIN p ON k.source IS NOT DISTINCT FROM p.source),
      i AS (SELECT *, CASE WHEN weighed > 0 THEN (target - (before * {config.cap})::DOUBLE) / weighed::DOUBLE END AS lv FROM h),
      j AS (SELECT *, min(CASE WHEN lv * odds <= {config.cap} THEN -class END) OVER (PARTITION BY source) AS cut_at FROM i),
      m AS (SELECT *, max(CASE WHEN -class = cut_at THEN lv END) OVER (PARTITION BY source) AS cut_lv FROM j),
      n AS (SELECT *, CASE WHEN class < 0 THEN 0 WHEN cut_at IS NULL OR -class < cut_at OR cut_lv * odds >= {config.cap} - 1e-9 THEN {config.cap}::DOUBLE ELSE cut_lv * odds END AS copies FROM m),
      q AS (SELECT *, target - (sum(floor(copies)::BIGINT * words) OVER (PARTITION BY source))::DOUBLE AS gap0 FROM n),
      g AS (SELECT e.doc_id, e.source, size, source_size, target, floor(copies)::BIGINT AS whole, copies - floor(copies) AS share, gap0,
          CASE WHEN copies > floor(copies) THEN ((u / (1 - u)) * ((1 - (copies - floor(copies))) / (copies - floor(copies)))) / (1 + (u / (1 - u)) * ((1 - (copies - floor(copies))) / (copies - floor(copies)))) ELSE 2 END AS r
          FROM e JOIN q ON e.source IS NOT DISTINCT FROM q.source AND e.class = q.class),
      {", ".join(steps)}
      SELECT doc_id, size, source_size, target, size * (CASE WHEN size > 0 THEN whole + ({taken})::BIGINT ELSE 0 END) AS taken FROM g{config.passes - 1}"""
