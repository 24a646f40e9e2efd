"""N-gram Jaccard self-join by grouped prefixes, as near-duplicate components.

A document is its set of distinct 5-word shingles. Two link when 100 * |intersection| >= percent *
|union|. Any two that link share a shingle among the first n - ceil(n * percent / 100) + 1 of each
in one common order, the prefix. The order puts frequent shingles last, so that prefixes rarely meet
by common passages. Documents with the same prefix and size form a group; groups meet by shared
prefix shingles, pass size and position filters, and are expanded to their distinct members, which
pass a bitmap filter (a parity bitmap differs in no more places than the sets do) and are verified
on their whole sets.

Not all pairs are expanded. First each member is verified against the nearest of a few partners (its
neighbours at its prefix shingles, the first member of its own group), in rounds while many pairs
lie across components. A frequent shingle's groups are dealt to as many cells as the root of their number,
neighbours are those of a cell, and the cells' first ones are neighbours too, so that no key's rows
meet in one task; then all pairs from different components, found by joining the distinct
components of each shingle, are verified. So a group of copies costs its size, not the square, and
no link between components is lost.

Which shingles are frequent only changes the speed: any order gives the same result.

Edge cases: null text and texts without words have no shingles and link with nothing; shorter texts
than a shingle are one shingle; rows with a null doc_id get a null component; rows that share a
doc_id are one document, linked to all that any of them links to; an empty table gives an empty
result; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .components import components
from .scratch import bound_arrow, broadcast_if_small, counted, discard, materialize, release, table
from .textscan import SPACED, mix, small_batches, text_shingles


@dataclass(frozen=True)
class JoinConfig:
    """percent: least Jaccard similarity; words: of a shingle. The rest only steers speed: shingles
    seen at least frequent_least times are put last in the order, the frequent_most most frequent at
    most; rounds: of cheap links before all pairs across components are tried, done while these are
    more than `crowded` a shingle."""

    percent: int = 80
    words: int = 5
    frequent_least: int = 8
    frequent_most: int = 2_000_000
    rounds: int = 1
    crowded: int = 100


def _summed(marks: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct marks, sorted, and the sums of their counts."""
    m, c = np.concatenate(marks), np.concatenate(counts)
    order = np.argsort(m, kind="stable")
    m, c = m[order], c[order]
    at = np.flatnonzero(np.concatenate([[True], m[1:] != m[:-1]])) if len(m) else np.empty(0, np.int64)
    return m[at], np.add.reduceat(c, at, dtype=np.int64) if len(m) else c


def _deal_marks(config: JoinConfig, bits: int):
    """(part, once, marks, counts): the shingles' leading 32 + bits bits; the first `bits` are the part, the
    others stand as 4-byte numbers, those seen once apart from those with counts. A task adds up
    what it sees before it sends it, so a passage of very many documents costs a number per task."""

    def told(marks: np.ndarray, counts: np.ndarray) -> pa.RecordBatch:
        at = np.searchsorted(marks, np.arange((1 << bits) + 1, dtype=np.uint64) << np.uint64(32))
        full = np.flatnonzero(np.diff(at))
        low, n = marks.astype(np.uint32), np.minimum(counts, 2**32 - 1).astype(np.uint32)
        single = [n[at[p] : at[p + 1]] == 1 for p in full]
        cut = [low[at[p] : at[p + 1]] for p in full]
        blobs = [[x[o].tobytes() for x, o in zip(cut, single, strict=True)], [x[~o].tobytes() for x, o in zip(cut, single, strict=True)], [n[at[p] : at[p + 1]][~o].tobytes() for p, o in zip(full, single, strict=True)]]
        return pa.RecordBatch.from_arrays([pa.array(full, pa.int64()), *(pa.array(b, pa.binary()) for b in blobs)], ["part", "once", "marks", "counts"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        marks, counts, size = [], [], 0
        for batch in small_batches(batches, "text"):
            s, _ = text_shingles(batch.column(0), SPACED, config.words)
            m, n = np.unique(s >> np.uint64(32 - bits), return_counts=True)
            marks.append(m)
            counts.append(n)
            size += len(m)
            if size > _MARKS_HELD:
                yield told(*_summed(marks, counts))
                marks, counts, size = [], [], 0
        if size:
            yield told(*_summed(marks, counts))

    return run


def _count_marks(config: JoinConfig):
    def run(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        marks, counts = [np.empty(0, np.uint32)], [np.empty(0, np.int64)]
        for batch in batches:
            for once, often, n in zip(*(batch.column(i) for i in (1, 2, 3)), strict=True):
                marks += [np.frombuffer(once.as_buffer(), np.uint32), np.frombuffer(often.as_buffer(), np.uint32)]
                counts += [np.ones(len(marks[-2]), np.uint32), np.frombuffer(n.as_buffer(), np.uint32)]
        m, n = _summed(marks, counts)
        kept = n >= config.frequent_least
        yield pa.RecordBatch.from_arrays([pa.array(m[kept].astype(np.int64) + (key[0].as_py() << 32)), pa.array(n[kept])], ["mark", "n"])

    return run


@dataclass(frozen=True)
class Frequent:
    """Sorted marks (`lead` leading bits) of frequent shingles, and how often each was seen."""

    marks: np.ndarray
    seen: np.ndarray
    lead: int

    def find(self, shingles: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Whether each shingle is frequent, and its place among the marks."""
        mark = shingles >> np.uint64(64 - self.lead)
        at = np.minimum(np.searchsorted(self.marks, mark), max(len(self.marks) - 1, 0))
        return (self.marks[at] == mark if len(self.marks) else np.zeros(len(mark), bool)), at


def frequent_shingles(docs: DataFrame, config: JoinConfig = JoinConfig()) -> Frequent:
    """All shingles of all texts are counted, in parts of about four million; how many frequent ones
    are kept is bounded by frequent_most, because every worker holds them."""
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    bits = min(24, max(5, (size // 6 // (4 << 20)).bit_length()))
    parts = docs.select("text").mapInArrow(_deal_marks(config, bits), "part long, once binary, marks binary, counts binary")
    often = parts.groupBy("part").applyInArrow(_count_marks(config), "mark long, n long")
    top = often.orderBy(F.desc("n"), "mark").limit(config.frequent_most).toArrow()
    marks, seen = (top.column(i).to_numpy() for i in (0, 1)) if top.num_rows else (np.empty(0, np.int64),) * 2
    order = np.argsort(marks)
    return Frequent(marks[order].astype(np.uint64), np.minimum(seen[order], 2**32 - 1).astype(np.uint32), 32 + bits)


#: 64-bit numbers of the short parity bitmap.
_FOLDS = 8
#: Earlier meeting places of a row at which a pair is looked for, so that it isn't told again.
_BEFORE = 4
#: Distinct marks that a counting task holds before it sends their sums.
_MARKS_HELD = 1 << 20


def _signed(x: np.ndarray) -> int:
    return int(x.astype(np.uint64).view(np.int64))


def _describe(config: JoinConfig, frequent: Frequent):
    """doc_id, n, two sums that stand for the set, prefix key, prefix, how far the prefix reaches in the
    order, bitmap of the set's size, and a short bitmap of one size for all."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text"):
            s, at = text_shingles(batch.column(1), SPACED, config.words)
            n, fp1, fp2, pk, prefix, reach, bits, fold = [], [], [], [], [], [], [], []
            for d in range(batch.num_rows):
                u = np.unique(s[at[d] : at[d + 1]])
                early = len(u)
                n.append(len(u))
                fp1.append(_signed(mix(u).sum(dtype=np.uint64)))
                fp2.append(_signed(mix(u ^ np.uint64(0x5851F42D4C957F2D)).sum(dtype=np.uint64)))
                if len(u):
                    last, _ = frequent.find(u)
                    u, early = np.concatenate([u[~last], u[last]]) if last.any() else u, len(u) - int(last.sum())
                p = u[: len(u) - -(-len(u) * config.percent // 100) + 1] if len(u) else u
                pk.append(_signed(mix(p + np.uint64(0x2545F4914F6CDD1D)).sum(dtype=np.uint64)))
                prefix.append(p.tobytes())
                # half the last prefix shingle, below 0 where it is not a frequent one
                reach.append((int(p[-1]) >> 1) - (0 if len(p) > early else 1 << 63) if len(p) else 0)
                width = max(64, 1 << (2 * max(len(u), 1) - 1).bit_length())
                parity = np.bincount((u & np.uint64(width - 1)).astype(np.int64), minlength=width) & 1
                bits.append(np.packbits(parity.astype(np.uint8), bitorder="little").tobytes())
                parity = np.bincount((u & np.uint64(64 * _FOLDS - 1)).astype(np.int64), minlength=64 * _FOLDS) & 1
                fold.append(np.packbits(parity.astype(np.uint8), bitorder="little").view(np.int64))
            cols = [batch.column(0), pa.array(n, pa.int64()), pa.array(fp1, pa.int64()), pa.array(fp2, pa.int64()), pa.array(pk, pa.int64()), pa.array(prefix, pa.binary()), pa.array(reach, pa.int64()), pa.array(bits, pa.binary())]
            folds = np.array(fold).reshape(len(fold), _FOLDS)
            yield pa.RecordBatch.from_arrays([*cols, *(pa.array(folds[:, k]) for k in range(_FOLDS))], ["doc_id", "n", "fp1", "fp2", "pk", "prefix", "reach", "bits", *(f"f{k}" for k in range(_FOLDS))])

    return run


def _explode_prefix(frequent: Frequent):
    """Postings (token, cell, gid, n, pos). A frequent token is dealt to about as many cells as the root of
    how often it was seen, numbered from 1; others have the one cell 0."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "prefix", 2 << 20):
            blobs = batch.column(2).to_pylist()
            lengths = np.array([len(b) // 8 for b in blobs], dtype=np.int64)
            at = np.concatenate([[0], np.cumsum(lengths)])
            rows = np.repeat(np.arange(len(blobs)), lengths)
            pos = np.arange(at[-1]) - at[rows]
            tokens, gid = np.frombuffer(b"".join(blobs), np.uint64), batch.column(0).to_numpy()[rows]
            often, place = frequent.find(tokens)
            cell = np.zeros(len(tokens), np.int32)
            if often.any():
                cells = np.ceil(np.sqrt(frequent.seen[place[often]])).astype(np.uint64)
                cell[often] = (mix(gid[often].astype(np.uint64) ^ tokens[often]) % cells).astype(np.int32) + 1
            yield pa.RecordBatch.from_arrays([pa.array(tokens.view(np.int64)), pa.array(cell), pa.array(gid), pa.array(batch.column(1).to_numpy()[rows]), pa.array(pos)], ["token", "cell", "gid", "n", "pos"])

    return run


def _sets(config: JoinConfig):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text"):
            s, at = text_shingles(batch.column(1), SPACED, config.words)
            blobs = [np.unique(s[at[d] : at[d + 1]]).tobytes() for d in range(batch.num_rows)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(blobs, pa.binary())], ["doc_id", "hashes"])

    return run


def _bitmap_pass(config: JoinConfig):
    """Pairs (a, b, na, nb, bits_a, bits_b) that may link; distance is how many bits differ."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "bits_a", 4 << 20):
            keep, far = [], []
            columns = (batch.column(i).to_pylist() for i in range(2, 6))
            for row, (na, nb, x, y) in enumerate(zip(*columns, strict=True)):
                x, y = np.frombuffer(x, np.uint8), np.frombuffer(y, np.uint8)
                while len(x) > len(y):
                    x = x[: len(x) // 2] ^ x[len(x) // 2 :]
                while len(y) > len(x):
                    y = y[: len(y) // 2] ^ y[len(y) // 2 :]
                d = int(np.bitwise_count(x ^ y).sum())
                least = -(-config.percent * (na + nb) // (100 + config.percent))
                if d <= na + nb - 2 * least:
                    keep.append(row)
                    far.append(d)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(keep, pa.int64())), batch.column(1).take(pa.array(keep, pa.int64())), pa.array(far, pa.int64())], ["a", "b", "distance"])

    return run


def _exact_pass(config: JoinConfig):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "hashes_a", 8 << 20):
            keep = []
            for row in range(batch.num_rows):
                x, y = (np.frombuffer(batch.column(i)[row].as_buffer(), np.uint64) for i in (2, 3))
                both = len(np.intersect1d(x, y, assume_unique=True))
                if 100 * both >= config.percent * (len(x) + len(y) - both):
                    keep.append(row)
            yield pa.RecordBatch.from_arrays([batch.column(i).take(pa.array(keep, pa.int64())) for i in (0, 1)], ["u", "v"])

    return run


def _like_size(config: JoinConfig, a: str, b: str) -> Column:
    na, nb = F.col(f"{a}n"), F.col(f"{b}n")
    return (na * 100 >= nb * config.percent) & (nb * 100 >= na * config.percent)


def _verified(docs: DataFrame, marks: DataFrame, pairs: DataFrame, config: JoinConfig, best: bool) -> tuple[DataFrame, list[DataFrame]]:
    """The links (u, v) among pairs (a, b) of class ids, and the tables that they are read from; with
    best only the nearest partner of each class is tried."""
    bits = marks.select("doc_id", "n", "bits")
    rows = pairs.join(bits.toDF("a", "na", "bits_a"), "a").join(bits.toDF("b", "nb", "bits_b"), "b").select("a", "b", "na", "nb", "bits_a", "bits_b")
    near = rows.mapInArrow(_bitmap_pass(config), "a long, b long, distance long")
    if best:
        ways = near.select(F.explode(F.array(F.struct("a", "b", "distance"), F.struct(F.col("b").alias("a"), F.col("a").alias("b"), "distance"))).alias("w")).select("w.*")
        near = ways.groupBy("a").agg(F.min(F.struct("distance", "b")).alias("m")).select(F.least("a", "m.b").alias("a"), F.greatest("a", "m.b").alias("b")).distinct()
    near = materialize(near.select("a", "b"), "join-near")
    ids, n = counted(near.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct(), "join-ids")
    texts = docs.select("doc_id", "text").join(broadcast_if_small(ids, n), "doc_id", "left_semi")
    sets = materialize(texts.mapInArrow(_sets(config), "doc_id long, hashes binary"), "join-sets")
    discard(ids)
    whole = near.join(sets.toDF("a", "hashes_a"), "a").join(sets.toDF("b", "hashes_b"), "b").select("a", "b", "hashes_a", "hashes_b")
    return whole.mapInArrow(_exact_pass(config), "u long, v long"), [near, sets]


def _merged(settled: DataFrame, links: DataFrame, read_from: list[DataFrame]) -> tuple[DataFrame, int]:
    """settled (cid, comp) after further links between any cids: only components are walked again. And
    how many links there were between different components."""
    one, two = settled.toDF("u", "cu"), settled.toDF("v", "cv")
    between = links.join(one, "u").join(two, "v").select(F.col("cu").alias("u"), F.col("cv").alias("v"))
    moved = components(between)
    discard(*read_from)
    if not moved.links:
        discard(moved)
        return settled, 0
    out = materialize(settled.join(moved, F.col("comp") == F.col("node"), "left").select("cid", F.coalesce("component", "comp").alias("comp")), "join-settled")
    discard(settled, moved)
    return out, moved.links


def _sides(meetings: DataFrame, config: JoinConfig) -> tuple[DataFrame, DataFrame]:
    """(index, probe) of meetings (token, comp, gid, cid, n, rest, held): rows that may be the smaller and the
    larger partner of a pair whose first common shingle this is, by token and size bucket.

    From its first common shingle on, a document can share its `rest` shingles, and a pair of sizes n, k
    needs percent * (n + k) / (100 + percent). So the smaller needs twice its share of its own size,
    and the larger finds partners only up to a size that its rest allows: hi."""
    share = 100 + config.percent
    bucket = lambda x: F.floor(F.log(x.cast("double")) / F.lit(0.05)).cast("int")
    rows = meetings.select("token", "comp", "gid", "cid", "n", "rest", "held")
    index = rows.where(F.col("rest") * share >= 2 * config.percent * F.col("n")).withColumn("bucket", bucket(F.col("n")))
    lo = F.expr(f"(n * {config.percent} + 99) div 100")
    hi = F.least(F.expr(f"rest * {share} div {config.percent}") - F.col("n"), F.col("n"))
    probe = rows.withColumn("lo", lo).withColumn("hi", hi).where("lo <= hi")
    return index, probe.withColumn("bucket", F.explode(F.sequence(bucket(F.col("lo")), bucket(F.col("hi")))))


def _across(index: DataFrame, probe: DataFrame) -> DataFrame:
    """(token, bucket, a_comp, b_comp, nb, ways): where members of different components meet, and how many
    pairs of members that is. Grouped first, so no row stands for a pair within a component."""
    one = probe.groupBy("token", "bucket", F.col("comp").alias("a_comp")).agg(F.count(F.lit(1)).alias("na"))
    two = index.groupBy("token", "bucket", F.col("comp").alias("b_comp")).agg(F.count(F.lit(1)).alias("nb"))
    return one.join(two, ["token", "bucket"]).where("a_comp <> b_comp").select("token", "bucket", "a_comp", "b_comp", "nb", (F.col("na") * F.col("nb")).alias("ways"))


def _cross_pairs(index: DataFrame, probe: DataFrame, across: DataFrame, folds: DataFrame, config: JoinConfig) -> DataFrame:
    """Pairs (a, b) of different components that may link, and differ in no more places of
    their short bitmaps (doc_id, f0, ...) than linked sets do. Of the two, the one whose prefix ends
    earlier in the order shares at most `held`: what it has in common with the other and in its own
    prefix is in the other's prefix too. For the other one that does not hold. The component with most index rows at a
    place meets only the others' rows, so members of one large component are not held together.

    A pair that met at one of the _BEFORE places before this one in both rows' order is not told again: what
    it passes here it passed there, as rest and held only fall along the order. So a pair with many common
    shingles is told a few times at most, and no pair is lost."""
    place = ["token", "bucket"]
    most = across.select(*place, F.col("b_comp").alias("comp"), "nb").distinct().groupBy(*place).agg(F.max_by("comp", "nb").alias("most"))
    names = [f"f{k}" for k in range(_FOLDS)]
    maps = folds.select(F.col("doc_id").alias("cid"), "reach", *names)
    # rows of different texts under one doc_id have orders of their own
    order = Window.partitionBy("cid", "bucket", "gid", "reach", *names).orderBy(F.desc("rest"), F.desc("held"), "token")
    past = [f"t{k}" for k in range(1, _BEFORE + 1)]
    told = [F.lag("token", k).over(order).alias(f"t{k}") for k in range(1, _BEFORE + 1)]
    one = probe.join(most, place).join(maps, "cid").select("*", *told).select(*place, "most", "lo", "hi", *[F.col(c).alias(f"a_{c}") for c in ("comp", "cid", "n", "held", "reach", *names, *past)])
    two = index.join(most, place).join(maps, "cid").select("*", *told).select(*place, "most", *[F.col(c).alias(f"b_{c}") for c in ("comp", "cid", "n", "rest", "held", "reach", *names, *past)])
    share, both = 100 + config.percent, F.col("a_n") + F.col("b_n")
    differ = sum((F.bit_count(F.col(f"a_{c}").bitwiseXOR(F.col(f"b_{c}"))) for c in names), F.lit(0))
    fits = (F.col("a_comp") != F.col("b_comp")) & F.col("b_n").between(F.col("lo"), F.col("hi")) & (F.col("b_rest") * share >= config.percent * both)
    for x, y in ("ab", "ba"):
        fits = fits & ((F.col(f"{x}_reach") >= F.col(f"{y}_reach")) | (F.col(f"{x}_held") * share >= config.percent * both))
    fits = fits & (differ <= both - 2 * F.ceil(config.percent * both / float(share)))
    for c in past:
        fits = fits & ~F.coalesce(F.col(f"a_{c}").isin(*[F.col(f"b_{x}") for x in past]), F.lit(False))
    sides = (one, two.where("b_comp <> most")), (one.where("a_comp <> most"), two.where("b_comp = most"))
    pairs = [x.drop("most").join(y.drop("most"), place).where(fits) for x, y in sides]
    return pairs[0].unionByName(pairs[1]).select(F.least("a_cid", "b_cid").alias("a"), F.greatest("a_cid", "b_cid").alias("b"))


def _shared_prefixes(groups: DataFrame, frequent: Frequent, config: JoinConfig) -> DataFrame:
    """(token, cell, gid, n, rest, held, next, head) of prefix shingles that may stand in other groups'
    prefixes. groups: gid, n, prefix. rest: shingles from this place on; held: those without the
    prefix shingles of this group alone, which may still stand in others' suffixes, so it bounds only
    pairs with prefixes that reach further. next: the neighbour by size (gid, n) in the token's cell;
    head: the first row of one of a token's several cells."""
    postings = groups.select("gid", "n", "prefix").mapInArrow(_explode_prefix(frequent), "token long, cell int, gid long, n long, pos long")
    by_cell = Window.partitionBy("token", "cell")
    in_order = by_cell.orderBy("n", F.xxhash64("gid", "token"))
    common = postings.select("*", F.count(F.lit(1)).over(by_cell).alias("many"), F.lead(F.struct("gid", "n")).over(in_order).alias("next"), F.row_number().over(in_order).alias("place"))
    common = common.where("many > 1 OR cell > 0")
    suffix = F.expr(f"(n * {config.percent} + 99) div 100 - 1")
    after = Window.partitionBy("gid").orderBy(F.desc("pos"))
    return common.select("token", "cell", "gid", "n", (F.col("n") - F.col("pos")).alias("rest"), (suffix + F.row_number().over(after)).alias("held"), "next", F.expr("cell > 0 AND place = 1").alias("head"))


def _neighbours(shared: DataFrame, config: JoinConfig) -> DataFrame:
    """(a, b): each group with the next by size in its cells, and the heads of a token's cells among themselves."""
    beside = Window.partitionBy("token").orderBy("n", F.xxhash64("gid", "token"))
    heads = shared.where("head").select("gid", "n", F.lead(F.struct("gid", "n")).over(beside).alias("next"))
    pairs = shared.select("gid", "n", "next").unionByName(heads).where(F.col("next").isNotNull()).where(_like_size(config, "", "next."))
    return pairs.select(F.least("gid", "next.gid").alias("a"), F.greatest("gid", "next.gid").alias("b"))


def ngram_components(docs: DataFrame, config: JoinConfig = JoinConfig()) -> DataFrame:
    """One row per row of docs (doc_id, text): doc_id, n_shingles, component_id."""
    spark = docs.sparkSession
    bound_arrow(spark)
    frequent = frequent_shingles(docs, config)
    folds = [f"f{k}" for k in range(_FOLDS)]
    schema = "doc_id long, n long, fp1 long, fp2 long, pk long, prefix binary, reach long, bits binary, " + ", ".join(f"{f} long" for f in folds)
    marks = materialize(docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(_describe(config, frequent), schema), "join-marks")
    release(spark)
    some = marks.where("n > 0 AND doc_id IS NOT NULL")
    # classes of equal sets, groups of equal prefix and size; each is named by its least doc_id
    classes = some.groupBy("fp1", "fp2", "n", "pk").agg(F.min("doc_id").alias("cid"))
    groups = classes.groupBy("n", "pk").agg(F.min("cid").alias("gid"))
    classes = materialize(classes.join(groups, ["n", "pk"]), "join-classes")
    # postings: a group has those of its prefix once
    prefixes = some.groupBy("n", "pk").agg(F.min("doc_id").alias("gid"), F.first("prefix").alias("prefix"))
    shared = materialize(_shared_prefixes(prefixes, frequent, config), "join-shared")
    release(spark)
    settled = materialize(classes.select("cid", F.col("cid").alias("comp")).distinct(), "join-settled")
    # first links: each group with its neighbours by size at its shingles, each class with its group's first
    pairs = _neighbours(shared, config).unionByName(classes.where("cid <> gid").select(F.col("gid").alias("a"), F.col("cid").alias("b"))).distinct()
    reps = some.join(classes.select(F.col("cid").alias("doc_id"), "fp1", "fp2"), ["doc_id", "fp1", "fp2"], "left_semi").select("doc_id", "n", "reach", "bits", *folds)
    settled, _ = _merged(settled, *_verified(docs, reps, pairs, config, best=True))
    release(spark)
    meetings = shared.select("token", "cell", "gid", "n", "rest", "held").unionByName(
        classes.where("cid <> gid").select("gid", "n").distinct().select(F.xxhash64("gid", F.lit("group")).alias("token"), F.lit(0).alias("cell"), "gid", "n", F.col("n").alias("rest"), F.col("n").alias("held")))
    meetings = meetings.join(classes.select("gid", "cid"), "gid")
    for turn in range(config.rounds + 1):
        held = meetings.join(settled, "cid").select("token", "cell", "comp", "gid", "cid", "n", "rest", "held")
        index, probe = _sides(held, config)
        across = materialize(_across(index, probe), "join-across")
        size = across.agg(F.sum("ways").alias("ways"), F.countDistinct("token").alias("tokens")).first()
        if turn == config.rounds or (size["ways"] or 0) <= config.crowded * size["tokens"]:
            break
        # many pairs lie across components: first link more of them, each class with random neighbours at its shingles
        beside = Window.partitionBy("token", "cell").orderBy(F.xxhash64("cid", "token", F.lit(turn)))
        crowd = held.join(across.select("token").distinct(), "token", "left_semi")
        tried = crowd.withColumn("next", F.lead(F.struct("cid", "comp", "n")).over(beside)).where(F.col("comp") != F.col("next.comp"))
        tried = tried.where(_like_size(config, "", "next."))
        settled, found = _merged(settled, *_verified(docs, reps, tried.select(F.least("cid", "next.cid").alias("a"), F.greatest("cid", "next.cid").alias("b")).distinct(), config, best=True))
        if not found:
            break
        discard(across)
    release(spark)
    # then all that lies across components
    if size["ways"]:
        settled, _ = _merged(settled, *_verified(docs, reps, _cross_pairs(index, probe, across, reps, config).distinct(), config, best=False))
    discard(shared, across)
    release(spark)
    # rows that share a doc_id are one document
    rows = marks.select("doc_id", "n", "fp1", "fp2").join(classes.select("fp1", "fp2", "n", "cid"), ["fp1", "fp2", "n"], "left")
    twice = some.groupBy("doc_id").agg(F.count(F.lit(1)).alias("k")).where("k > 1").select("doc_id")
    own = rows.join(twice, "doc_id", "left_semi").where("cid <> doc_id").select(F.col("doc_id").alias("u"), F.col("cid").alias("v")).distinct()
    # such a doc_id need not name a class
    every = materialize(settled.unionByName(own.select(F.col("u").alias("cid"), F.col("u").alias("comp")).distinct()).groupBy("cid").agg(F.min("comp").alias("comp")), "join-settled")
    discard(settled)
    settled, _ = _merged(every, own, [])
    named = rows.join(settled, F.when(F.col("n") > 0, rows["cid"]) == settled["cid"], "left")
    out = materialize(named.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.coalesce("comp", rows["cid"], "doc_id")).alias("component_id")), "join-result")
    discard(marks, classes, settled)
    release(spark)
    return out


def op8_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_components(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op8_oracle() -> str:
    """All pairs that share a shingle, and reachability; for small tables."""
    return r"""WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
      s AS (SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
              ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(list_slice(w, i, i + 4), ' ')) END) AS g FROM d),
      c AS (SELECT min(doc_id) AS cid, g FROM s WHERE len(g) > 0 GROUP BY g),
      x AS (SELECT cid, len(g) AS n, unnest(g) AS t FROM c),
      links AS (SELECT a.cid AS u, b.cid AS v FROM x a JOIN x b ON a.t = b.t AND a.cid < b.cid
                WHERE 100 * a.n >= 80 * b.n AND 100 * b.n >= 80 * a.n
                GROUP BY a.cid, b.cid, a.n, b.n HAVING 180 * count(*) >= 80 * (a.n + b.n)),
      both_ways AS (SELECT u, v FROM links UNION ALL SELECT v, u FROM links),
      r AS (SELECT cid AS node, cid AS seen FROM c UNION SELECT r.node, e.v FROM r JOIN both_ways e ON r.seen = e.u)
      SELECT s.doc_id, len(s.g)::BIGINT AS n_shingles, coalesce(k.component, s.doc_id)::BIGINT AS component_id
      FROM s LEFT JOIN c ON c.g = s.g LEFT JOIN (SELECT node, min(seen) AS component FROM r GROUP BY node) k ON k.node = c.cid"""
