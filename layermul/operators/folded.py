"""C = A B with the rows of C folded in the cells that make them: for products whose entries are too many
to be kept or sent. Operands lie in the shared folder as blocks of rows of A and of columns of B; a cell
is a pair of them, read there, so no copy is dealt out and only a row's sums leave a cell."""

from __future__ import annotations

import gc
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from layermul.matrix import SparseMatrix
from layermul.session import configure, materialize

#: Entries of a block on average, of a tile of C, of a slice of it that is summed, and products made at once.
BLOCK_ENTRIES, TILE, SLICE, AT_ONCE = 3_500_000, 1 << 22, 1 << 17, 1 << 21
#: Time of a product by its place against that of a multiplication of dense rows.
SCATTERED = 400
#: Columns from which those of an inner index are added as one span.
LISTED = 16
#: Groups of alike rows in a block at most, rows of one on average at least, and inner indices by which they are alike.
GROUPS, GROUP_ROWS, FEATURES = 6, 256, 1000

_BLOCK = "block int, ids binary, known binary, sizes binary, names binary, codes binary, v binary, groups binary"
#: Types of values, by their bytes.
_WHOLE = {1: np.uint8, 2: np.uint16, 4: np.int32, 8: np.int64}
_FOLD = "i bigint, cnt bigint, total bigint, mix bigint"


def _alike(rows: np.ndarray, codes: np.ndarray, n: int) -> np.ndarray:
    """The group of each of n rows: rows of one share more of the frequent inner indices (k-means). Groups only decide
    how products are made; any others give the same ones."""
    groups = max(1, min(GROUPS, n // GROUP_ROWS))
    if groups == 1:
        return np.zeros(n, np.int64)
    count = np.bincount(codes)
    frequent = np.argsort(-count, kind="stable")[: max(1, min(FEATURES, (1 << 24) // n))]
    slot = np.full(len(count), -1)
    slot[frequent] = np.arange(len(frequent))
    some = slot[codes] >= 0
    x = np.zeros((n, len(frequent)), np.float32)
    x[rows[some], slot[codes[some]]] = np.sqrt(np.log((n + 1) / count[codes[some]]))
    x /= np.sqrt((x * x).sum(1, keepdims=True)) + 1e-9
    centres = x[np.random.default_rng(0).choice(n, groups, replace=False)]
    for _ in range(6):
        group = (x @ centres.T - (centres * centres).sum(1) / 2).argmax(1)
        member = (group == np.arange(groups)[:, None]).astype(np.float32)
        size = member.sum(1, keepdims=True)
        centres = np.where(size > 0, member @ x / np.maximum(size, 1), centres)
    return group


def _packed(key: tuple, rows: pa.Table) -> pa.Table:
    """One row: a block's ids, entries by row, the inner indices that they name by code, and rows in groups of alike ones."""
    i, ks, vs = (rows.column(c).combine_chunks() for c in ("i", "ks", "vs"))
    k, v = (x.flatten().to_numpy(zero_copy_only=False) for x in (ks, vs))
    size = ks.value_lengths().to_numpy(zero_copy_only=False)
    if v.min() <= 0:
        raise ValueError("values must be positive")
    known = np.repeat(i.is_valid().to_numpy(zero_copy_only=False), size)
    i = np.repeat(i.fill_null(0).to_numpy(zero_copy_only=False), size)
    names, codes = np.unique(k, return_inverse=True)
    order = np.lexsort((codes, i, known))
    i, known, codes, v = i[order], known[order], codes[order].astype(np.int32), v[order]
    first = np.flatnonzero(np.concatenate([[True], (i[1:] != i[:-1]) | (known[1:] != known[:-1]) | (codes[1:] != codes[:-1])]))
    i, known, codes, v = i[first], known[first], codes[first], np.add.reduceat(v, first)
    first = np.flatnonzero(np.concatenate([[True], (i[1:] != i[:-1]) | (known[1:] != known[:-1])]))
    sizes = np.diff(np.append(first, len(i))).astype(np.int32)
    v = v.astype(next(t for t in _WHOLE.values() if v.max() <= np.iinfo(t).max))
    rows = np.repeat(np.arange(len(first)), sizes)
    group = _alike(rows, codes, len(first))
    order = np.argsort(group, kind="stable")
    entries = np.argsort(np.argsort(order)[rows], kind="stable")
    first, sizes, codes, v, ids, known = first[order], sizes[order], codes[entries], v[entries], i[first[order]], known[first[order]]
    parts = [ids, known, sizes, names, codes, v, np.bincount(group).astype(np.int32)]
    return pa.table([pa.array([key[0].as_py()], pa.int32()), *(pa.array([p.tobytes()], pa.binary()) for p in parts)], ["block", "ids", "known", "sizes", "names", "codes", "v", "groups"])


@dataclass(frozen=True)
class _Block:
    ids: np.ndarray
    known: np.ndarray
    bounds: np.ndarray
    names: np.ndarray
    codes: np.ndarray
    v: np.ndarray
    groups: np.ndarray

    @classmethod
    def of(cls, ids: bytes, known: bytes, sizes: bytes, names: bytes, codes: bytes, v: bytes, groups: bytes) -> _Block:
        codes = np.frombuffer(codes, np.int32)
        bounds = np.concatenate([[0], np.cumsum(np.frombuffer(sizes, np.int32), dtype=np.int64)])
        return cls(np.frombuffer(ids, np.int64), np.frombuffer(known, bool), bounds, np.frombuffer(names, np.int64), codes, np.frombuffer(v, _WHOLE[len(v) // len(codes)]), np.concatenate([[0], np.cumsum(np.frombuffer(groups, np.int32), dtype=np.int64)]))

    @cached_property
    def rows(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.ids), dtype=np.int32), np.diff(self.bounds))

    @cached_property
    def counts(self) -> np.ndarray:
        return np.bincount(self.codes, minlength=len(self.names))

    def by_code(self) -> tuple[np.ndarray, np.ndarray]:
        """Rows and values in order of codes and rows."""
        at, by = int(self.v.max()).bit_length(), len(self.ids).bit_length()
        key = self.codes.astype(np.int64)
        key <<= by
        key |= self.rows
        if at + by + len(self.names).bit_length() > 63:
            order = np.argsort(key)  # no two are equal
            return self.rows[order], self.v[order]
        key <<= at
        key |= self.v.astype(np.int64)
        key.sort()
        return (key >> at & ((1 << by) - 1)).astype(np.int32), (key & ((1 << at) - 1)).astype(self.v.dtype)


class _Sums:
    """(cnt, those of them in columns that are not null, total, mix) of rows of C, and of its columns if both."""

    def __init__(self, a: _Block, b: _Block, modulus: int, wide: type, both: bool):
        self.a, self.b, self.both, m = a, b, both, len(b.ids)
        self.rows_weight, self.columns_weight = (np.stack([np.ones(len(x.ids), wide), np.where(x.known, x.ids % modulus, 0).astype(wide)]) for x in (a, b))
        self.step = min(255, max(1, SLICE // m))  # rows at once: a column's count of them fits a byte
        self.wide, self.found = np.empty((self.step, m), wide), np.zeros((self.step, -(-m // 1024) * 1024), bool)
        self.columns = np.zeros((4, m), np.int64)

    def add(self, part: np.ndarray, at: int) -> np.ndarray:
        """The sums of a few rows of C, which are those of a from the at-th on."""
        n, m = part.shape
        wide, found, out = self.wide[:n], self.found[:n], np.empty((4, n), np.int64)
        wide[:] = part
        np.not_equal(part, 0, out=found[:, :m])
        # eight bytes at once, 128 times in each
        out[0] = found.view(np.uint64).reshape(n, -1, 128).sum(2).view(np.uint8).sum(1, dtype=np.int64)
        out[1] = out[0] if self.b.known.all() else np.count_nonzero(found[:, :m][:, self.b.known], axis=1)
        out[2:] = self.columns_weight @ wide.T
        if self.both:
            known, count = self.a.known[at : at + n], found.view(np.uint8).sum(0, dtype=np.uint8)[:m]
            self.columns[0] += count
            self.columns[1] += count if known.all() else np.count_nonzero(found[known, :m], axis=0)
            self.columns[2:] += (self.rows_weight[:, at : at + n] @ wide).astype(np.int64)
        return out


def _batch(block: _Block, rows: slice, sums: np.ndarray) -> pa.RecordBatch:
    keep = sums[0] > 0
    count, told, total, mix = sums[:, keep]
    columns = [pa.array(block.ids[rows][keep], mask=~block.known[rows][keep]), pa.array(count), pa.array(total), pa.array(mix, mask=told == 0)]
    return pa.RecordBatch.from_arrays(columns, ["i", "cnt", "total", "mix"])


def _most(a: _Block, b: _Block) -> float:
    """No entry of C, and no sum on the way to it, exceeds this."""
    sums, norms, largest = zip(*((np.add.reduceat(v, x.bounds[:-1]).max(), np.add.reduceat(v * v, x.bounds[:-1]).max() ** 0.5, v.max()) for x in (a, b) for v in [x.v.astype(np.float64)]), strict=True)
    return 1.001 * float(min(sums[0] * largest[1], largest[0] * sums[1], norms[0] * norms[1]))


class _Spans:
    """Columns and values of some inner indices, each a number of its own, as bytes of all of an index that are put
    together quickly."""

    def __init__(self, rows: np.ndarray, v: np.ndarray, start: np.ndarray, counts: np.ndarray, kind: type, shift: int):
        self.shift, self.kind, self.counts = shift, kind, counts
        self.type = np.uint32 if shift + int(v.max(initial=0)).bit_length() <= 32 else np.uint64
        packed = rows.astype(self.type)
        packed |= v.astype(self.type) << self.type(shift)
        self.spans = [packed[lo:hi].tobytes() for lo, hi in zip(start.tolist(), (start + counts).tolist(), strict=True)]

    def add(self, c: np.ndarray, rows: np.ndarray, slots: np.ndarray, v: np.ndarray) -> None:
        """Adds v times a span to each of the rows of c, which come in order: the spans of a row go to it together,
        while it is in a core's cache."""
        counts = self.counts[slots]
        ends = np.cumsum(counts)
        parts = (ends - 1) // AT_ONCE
        first = np.flatnonzero(np.concatenate([[True], (rows[1:] != rows[:-1]) | (parts[1:] != parts[:-1])]))
        sizes, bounds = np.add.reduceat(counts, first).tolist(), [*first.tolist(), len(rows)]
        columns, values, numbers = (np.empty(max(sizes), t) for t in (np.intp, self.kind, self.type))
        taken, mask, shift = slots.tolist(), self.type((1 << self.shift) - 1), self.type(self.shift)
        for row, lo, hi, n in zip(rows[first].tolist(), bounds, bounds[1:], sizes, strict=False):
            packed = np.frombuffer(b"".join(map(self.spans.__getitem__, taken[lo:hi])), self.type)
            at, value, number = columns[:n], values[:n], numbers[:n]
            at[:] = np.bitwise_and(packed, mask, out=number)
            value[:] = np.right_shift(packed, shift, out=number)
            value *= np.repeat(v[lo:hi], counts[lo:hi])
            np.add.at(c[row], at, value)


def _add_single(c: np.ndarray, rows: np.ndarray, at: np.ndarray, v: np.ndarray, start: np.ndarray, counts: np.ndarray, columns: np.ndarray, values: np.ndarray) -> None:
    """Adds v times the columns and values of inner indices to the rows of c, one by one."""
    flat, base, count = c.reshape(-1), rows.astype(np.int64) * c.shape[1], counts[at]
    ends = np.cumsum(count)
    i = 0
    while i < len(at):
        j = max(i + 1, int(np.searchsorted(ends, (ends[i - 1] if i else 0) + AT_ONCE, "right")))
        reach = count[i:j]
        entries = np.repeat(start[at[i:j]] - (np.cumsum(reach) - reach), reach) + np.arange(reach.sum())
        np.add.at(flat, np.repeat(base[i:j], reach) + columns[entries], np.repeat(v[i:j], reach) * values[entries])
        i = j


def _folds(a: _Block, b: _Block, modulus: int, both: bool = False) -> Iterator[pa.RecordBatch]:
    """(i, cnt, total, mix) of the rows of a over the columns of b; both: and of the columns over the rows,
    which are the rows of the mirrored cell where b's columns are rows of a's matrix."""
    _, ia, ib = np.intersect1d(a.names, b.names, assume_unique=True, return_indices=True)
    if not len(ia):
        return
    n, m = len(a.ids), len(b.ids)
    most = _most(a, b)  # the least type that is exact
    kind = np.float32 if most < 2**24 else np.float64 if most < 2**53 else np.int64
    wide = np.float64 if most * max(n, m) * modulus < 2**53 else np.int64
    inner = np.full(len(a.names), -1)  # number of a's code among the shared ones
    inner[ia] = np.arange(len(ia))
    # entries of b by inner index, and how many of them are in each of its groups
    rows_b, v_b = b.by_code()
    number, groups = np.full(len(b.names), -1, np.int32), len(b.groups) - 1
    number[ib] = np.arange(len(ib))
    cell_b = np.repeat(number, b.counts)
    taken = np.flatnonzero(cell_b >= 0)
    cell_b, rows_b, v_b = cell_b[taken].astype(np.int32 if len(ib) * groups < 2**31 else np.int64), rows_b[taken], v_b[taken]
    del taken
    order = np.argsort(ib)
    start = np.empty(len(ib), np.int64)
    start[order] = np.cumsum(b.counts[ib[order]]) - b.counts[ib[order]]
    cell_b *= groups
    cell_b += np.repeat(np.arange(groups, dtype=np.int32), np.diff(b.groups))[rows_b]
    count_b = np.bincount(cell_b, minlength=len(ib) * groups).reshape(-1, groups)
    begin_b = start[:, None] + np.cumsum(count_b, axis=1) - count_b
    packs = m.bit_length() + int(b.v.max()).bit_length() < 64
    tile = max(1, TILE // m)
    sums, space = _Sums(a, b, modulus, wide, both), np.empty((min(n, tile), m), kind)

    def dense(group: int, picked: np.ndarray) -> np.ndarray:
        """Inner indices as rows over the columns of a group of b."""
        count = count_b[picked, group]
        entries = np.repeat(begin_b[picked, group] - (np.cumsum(count) - count), count) + np.arange(count.sum())
        right = np.zeros((len(picked), b.groups[group + 1] - b.groups[group]), kind)
        right[np.repeat(np.arange(len(picked)), count), rows_b[entries] - b.groups[group]] = v_b[entries]
        return right

    for top, end in zip(a.groups.tolist(), a.groups[1:].tolist(), strict=False):
        if top == end:
            continue
        # inner indices of many products are multiplied as dense rows, those of fewer by spans of columns, the rest one by one
        count_a = np.bincount(a.codes[a.bounds[top] : a.bounds[end]], minlength=len(a.names))[ia]
        often = count_a[:, None] * count_b * SCATTERED > (end - top) * np.diff(b.groups)
        heavy = [np.flatnonzero(often[:, g]) for g in range(groups)]
        strip = max(1, 4 * TILE // max(m, tile))
        kept = [dense(g, x) if len(x) <= strip else None for g, x in enumerate(heavy)]
        rest = ~often & (count_a > 0)[:, None]
        left_over = np.flatnonzero(rest.reshape(-1)[cell_b])
        rows_s, v_s = rows_b[left_over], v_b[left_over]
        count_s = (count_b * rest).sum(1)
        start_s = np.empty(len(ib), np.int64)
        start_s[order] = np.cumsum(count_s[order]) - count_s[order]
        listed = (count_s >= LISTED) & packs
        slot = np.cumsum(listed) - 1
        spans = _Spans(rows_s, v_s, start_s[listed], count_s[listed], kind, m.bit_length()) if packs else None
        v_s = v_s.astype(kind)
        for lo in range(top, end, tile):
            hi = min(end, lo + tile)
            one = slice(a.bounds[lo], a.bounds[hi])
            at, rows, v = inner[a.codes[one]], a.rows[one] - lo, a.v[one].astype(kind)
            some = np.flatnonzero(at >= 0)
            at, rows, v = at[some], rows[some], v[some]
            c = space[: hi - lo]
            for g, picked in enumerate(heavy):
                columns, place = c[:, b.groups[g] : b.groups[g + 1]], np.full(len(ib), -1)
                place[picked] = np.arange(len(picked))
                if kept[g] is None or not len(picked):
                    columns[:] = 0
                where = place[at]
                for s in range(0, len(picked), strip):
                    some = np.flatnonzero((where >= s) & (where < s + strip))
                    left = np.zeros((hi - lo, min(strip, len(picked) - s)), kind)
                    left[rows[some], where[some] - s] = v[some]
                    if kept[g] is None:
                        columns += left @ dense(g, picked[s : s + strip])
                    else:
                        np.matmul(left, kept[g], out=columns)
            some = np.flatnonzero(~listed[at] & (count_s[at] > 0))
            single, owner, factor = at[some], rows[some], v[some]
            some = np.flatnonzero(listed[at])
            at, rows, v = slot[at[some]], rows[some], v[some]
            out = np.empty((4, hi - lo), np.int64)
            for x in range(0, hi - lo, sums.step):
                part = c[x : x + sums.step]
                some = slice(*np.searchsorted(rows, (x, x + sums.step)))
                if some.start < some.stop:
                    spans.add(part, rows[some] - x, at[some], v[some])
                some = slice(*np.searchsorted(owner, (x, x + sums.step)))
                _add_single(part, owner[some] - x, single[some], factor[some], start_s, count_s, rows_s, v_s)
                out[:, x : x + len(part)] = sums.add(part, lo + x)
            yield _batch(a, slice(lo, hi), out)
    if both:
        yield _batch(b, slice(None), sums.columns)


def _blocks(lists: DataFrame, entries: int, name: str) -> DataFrame:
    """lists (i, ks, vs) as blocks of whole rows, dealt out by hash of i."""
    n = max(1, -(-entries // BLOCK_ENTRIES))
    packed = lists.where(F.size("ks") > 0).withColumn("block", F.pmod(F.xxhash64("i"), F.lit(n)).cast("int")).groupBy("block").applyInArrow(_packed, _BLOCK)
    out = materialize(packed, f"{name}-blocks", "zstd", 1)  # so that no two blocks are always read together
    _collect(out)
    return out


def _collect(df: DataFrame) -> None:
    """Spark deletes the shuffle files of plans that nothing refers to when the driver collects garbage."""
    gc.collect()
    df.sparkSession.sparkContext._jvm.System.gc()


def _lists(df: DataFrame, i: str, k: str) -> DataFrame:
    if df.schema["v"].dataType.simpleString() not in ("tinyint", "smallint", "int", "bigint"):
        raise ValueError("values must be whole")
    found = df.groupBy(F.col(i).alias("i")).agg(F.collect_list(F.struct(F.col(k).alias("k"), F.col("v").cast("bigint").alias("v"))).alias("e"))
    return found.select("i", F.col("e.k").alias("ks"), F.col("e.v").alias("vs"))


def folded_rows(a: SparseMatrix, b: SparseMatrix, modulus: int = 97) -> DataFrame:
    """(i, cnt, total, mix) of the rows of A B: entries, their sum, and their sum weighted by j mod modulus.
    Values must be whole and positive, so that no entry cancels out."""
    if a.ncols != b.nrows:
        raise ValueError(f"inner dimensions differ: {a.ncols} and {b.nrows}")
    return folded_lists(_lists(a.df, "i", "j"), a.nnz(), _lists(b.df, "j", "i"), b.nnz(), modulus)


def folded_lists(rows: DataFrame, n_rows: int, columns: DataFrame | None = None, n_columns: int = 0, modulus: int = 97) -> DataFrame:
    """The same of rows of A and columns of B as lists: i (of columns: j) bigint, ks (inner indices, or any
    whole numbers that stand for them one to one) and vs array<bigint>, about n_rows and n_columns entries in all.
    Entries that stand twice, also in lists of one i, are summed. Without columns, of A times its transpose."""
    spark = configure(rows.sparkSession)
    # one pair of blocks at once goes to a Python worker
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", 8 << 20)
    left = _blocks(rows, n_rows, "left")
    right = left if columns is None else _blocks(columns, n_columns, "right")
    other = right.toDF(*[f"{c}_b" for c in right.columns])
    pairs = left.hint("shuffle_replicate_nl").crossJoin(other)
    if columns is None:  # equal to its transpose: a cell folds its mirror too
        pairs = pairs.where("block <= block_b")

    square = columns is None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        read: dict[tuple[str, int], _Block] = {}

        def block(batch: pa.RecordBatch, row: int, first: int) -> _Block:
            key = first, batch.column(first)[row].as_py()
            if key not in read:
                for old in [k for k in read if k[0] == first][: -3 if first else None]:  # one of A's, four of B's
                    del read[old]
                read[key] = _Block.of(*(batch.column(first + 1 + x)[row].as_py() for x in range(7)))
            return read[key]

        for batch in batches:
            for row in range(batch.num_rows):
                mirrored = square and batch.column(0)[row] != batch.column(8)[row]
                yield from _folds(block(batch, row, 0), block(batch, row, 8), modulus, mirrored)

    return pairs.mapInArrow(run, _FOLD).groupBy("i").agg(F.sum("cnt").alias("cnt"), F.sum("total").alias("total"), F.sum("mix").alias("mix"))
