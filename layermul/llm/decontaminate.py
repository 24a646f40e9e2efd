"""Benchmark decontamination: size-partitioned MinHash containment search with exact verification.

An item is contained in a document when at least `percent` of its distinct word shingles stand in
the document. Items are partitioned by their number of shingles q; an item's MinHash sketch is its
bottom q - ceil(q * percent / 100) + 1 shingle hashes, the smallest sketch that a document with
enough of the item can't miss, however long the document is. So the search loses nothing: every
document is probed whole, only documents with at least ceil(q * percent / 100) shingles are
candidates of a size class, and each candidate is verified on the item's whole shingle set.

Size classes are powers of two of the shingles that a document needs; each has a sketch table of its
own, which texts too short for its smallest item are not looked up in. Items are held by every worker
while they have at most `held_most` shingles in all (counted before); a larger benchmark is dealt by
hash to as many parts as it takes, and the documents are searched once for each.

Edge cases: null text is empty and contains nothing; an item without words is in no document; an
item shorter than a shingle is one run of its own length and must stand in the document as such;
repeated rows of either table each give their own rows; empty tables give an empty result; extra
columns are ignored.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .scratch import bound_arrow, discard, materialize, table
from .textscan import ALNUM, find_words, grams, hash_words, shingles, small_batches, text_bytes

RESULT = "doc_id long, item_id long, n_item long, n_shared long"


@dataclass(frozen=True)
class ContainmentConfig:
    """percent: of an item's shingles; words: of a shingle; held_most: shingles of items that a worker
    holds at once, or one item if that has more."""

    percent: int = 80
    words: int = 5
    held_most: int = 4_000_000


def _hashed(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    data, offsets = text_bytes(column)
    starts, ends, bounds = find_words(data, offsets, ALNUM)
    return hash_words(data, starts, ends), bounds


def _item_sets(config: ContainmentConfig):
    """item_id, length (words of its shingles), hashes (sorted, distinct)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text"):
            words, bounds = _hashed(batch.column(1))
            s, at = shingles(words, bounds, config.words)
            blobs = [np.unique(s[at[i] : at[i + 1]]).tobytes() for i in range(batch.num_rows)]
            length = np.minimum(np.diff(bounds), config.words)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(length, pa.int64()), pa.array(blobs, pa.binary())], ["item_id", "length", "hashes"])

    return run


def item_sets(items: DataFrame, config: ContainmentConfig) -> DataFrame:
    bound_arrow(items.sparkSession)
    rows = items.select(F.col("item_id").cast("long"), "text").mapInArrow(_item_sets(config), "item_id long, length long, hashes binary")
    return materialize(rows.where("length > 0"), "items")


def _sketch_size(q: np.ndarray | int, percent: int):
    """How many of q shingles a document may miss, and one more."""
    return q - -(-q * percent // 100) + 1


class _Searcher:
    """Items by size class, ready to probe batches of documents."""

    def __init__(self, ids: list[int], lengths: list[int], sets: list[np.ndarray], config: ContainmentConfig):
        self.ids, self.sets, self.config = ids, sets, config
        self.needs = np.array([-(-len(s) * config.percent // 100) for s in sets], dtype=np.int64)
        self.lengths = np.array(lengths, dtype=np.int64)
        #: per class: the fewest shingles that one of its items needs, its sketch hashes in order, and whose they are
        self.classes: list[tuple[int, np.ndarray, np.ndarray]] = []
        self.seen = np.zeros(1 << 22, bool)
        size = np.array([int(n).bit_length() for n in self.needs], dtype=np.int64)
        for c in np.unique(size):
            own = np.flatnonzero(size == c)
            sketch = [sets[i][: _sketch_size(len(sets[i]), config.percent)] for i in own]
            hashes, owner = np.concatenate(sketch), np.repeat(own, [len(h) for h in sketch])
            by = np.argsort(hashes, kind="stable")
            self.classes.append((int(self.needs[own].min()), hashes[by], owner[by]))
            self.seen[hashes >> np.uint64(42)] = True

    def _probe(self, s: np.ndarray, text: np.ndarray, length_ok: np.ndarray, room: np.ndarray) -> set[tuple[int, int]]:
        """(text, item) that share a sketch hash; room: shingles of each text."""
        maybe = np.flatnonzero(self.seen[s >> np.uint64(42)])
        out: set[tuple[int, int]] = set()
        for need, hashes, owner in self.classes:
            at = maybe[room[text[maybe]] >= need]
            lo, hi = np.searchsorted(hashes, s[at], "left"), np.searchsorted(hashes, s[at], "right")
            hit = np.flatnonzero(hi > lo)
            out |= {(int(t), int(i)) for a, b, t in zip(lo[hit], hi[hit], text[at[hit]], strict=True) for i in owner[a:b] if length_ok[i]}
        return out

    def search(self, column: pa.Array) -> list[tuple[int, int, int]]:
        """(row, item, shared shingles) of every contained item."""
        words, bounds = _hashed(column)
        s, at = shingles(words, bounds, self.config.words)
        text = np.repeat(np.arange(len(column)), np.diff(at))
        found = []
        full = self.lengths >= self.config.words
        distinct: dict[int, np.ndarray] = {}
        room = np.diff(at)
        for row, item in sorted(self._probe(s, text, full, room)):
            q = len(self.sets[item])
            if room[row] < self.needs[item]:
                continue
            if row not in distinct:
                distinct = {row: np.unique(s[at[row] : at[row + 1]])}
            shared = len(np.intersect1d(self.sets[item], distinct[row], assume_unique=True))
            if 100 * shared >= self.config.percent * q:
                found.append((row, item, shared))
        for length in np.unique(self.lengths[~full]):
            g, where = grams(words, bounds, int(length))
            found += [(row, item, 1) for row, item in sorted(self._probe(g, where, self.lengths == length, np.ones(len(column), np.int64)))]
        return found


def _searchers(sets: DataFrame, config: ContainmentConfig) -> Iterator[_Searcher]:
    """The items in parts of about held_most shingles, one part at a time on the driver."""
    facts = sets.agg(F.sum(F.octet_length("hashes") / 8).alias("shingles"), F.count(F.lit(1)).alias("items")).first()
    total = facts["shingles"] or 0
    parts = 1 if total <= config.held_most else min(facts["items"], -(-5 * int(total) // (4 * max(config.held_most, 1))))
    dealt = F.pmod(F.xxhash64("hashes", F.coalesce("item_id", F.lit(-1))), F.lit(parts))
    for p in range(parts):
        rows = (sets if parts == 1 else sets.where(dealt == p)).toArrow()
        if rows.num_rows or parts == 1:
            hashes = [np.frombuffer(b, np.uint64) for b in rows.column("hashes").to_pylist()]
            yield _Searcher(rows.column("item_id").to_pylist(), rows.column("length").to_pylist(), hashes, config)


def _pairs(searcher: _Searcher) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text"):
            found = searcher.search(batch.column(1))
            rows, items = [f[0] for f in found], [f[1] for f in found]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).take(pa.array(rows, pa.int64())), pa.array([searcher.ids[i] for i in items], pa.int64()),
                 pa.array([len(searcher.sets[i]) for i in items], pa.int64()), pa.array([f[2] for f in found], pa.int64())],
                ["doc_id", "item_id", "n_item", "n_shared"])

    return run


def _clean(searcher: _Searcher) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text"):
            keep = np.ones(batch.num_rows, bool)
            keep[[f[0] for f in searcher.search(batch.column(batch.schema.get_field_index("text")))]] = False
            yield batch.filter(pa.array(keep))

    return run


def contained_items(docs: DataFrame, items: DataFrame, config: ContainmentConfig = ContainmentConfig()) -> DataFrame:
    """(doc_id, item_id, n_item, n_shared, containment) for every document that contains an item."""
    sets = item_sets(items, config)
    rows = docs.select(F.col("doc_id").cast("long"), "text")
    found: DataFrame | None = None
    for searcher in _searchers(sets, config):
        if found is not None:  # the part before is written before the next one is read
            found = materialize(found, "contained")
        one = rows.mapInArrow(_pairs(searcher), RESULT)
        found = one if found is None else found.unionByName(one)
    discard(sets)
    return found.withColumn("containment", F.col("n_shared") / F.col("n_item"))


def without_items(docs: DataFrame, items: DataFrame, config: ContainmentConfig = ContainmentConfig()) -> DataFrame:
    """The rows of docs, all columns, that contain no item."""
    sets = item_sets(items, config)
    left, before = docs, None
    for searcher in _searchers(sets, config):
        if left is not docs:
            written = materialize(left, "without")
            if before is not None:
                discard(before)
            left = before = written
        left = left.mapInArrow(_clean(searcher), docs.schema)
    discard(sets)
    return left


def op1_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contained_items(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark").select("item_id", "text"))


def op1_oracle() -> str:
    words = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
    grams_of = "unnest(list_distinct(list_transform(range(1, len(w) - k + 2), lambda i: array_to_string(list_slice(w, i, i + k - 1), ' '))))"
    return f"""WITH b AS (SELECT item_id, least(len({words}), 5) AS k, {words} AS w FROM benchmark),
      q AS (SELECT item_id, k, {grams_of} AS g FROM b WHERE k > 0),
      n AS (SELECT item_id, count(*) AS n_item FROM q GROUP BY item_id),
      d AS (SELECT doc_id, {words} AS w FROM documents),
      x AS (SELECT doc_id, k, {grams_of} AS g FROM d CROSS JOIN (SELECT DISTINCT k FROM b WHERE k > 0) WHERE len(w) >= k)
      SELECT doc_id, item_id, n_item::BIGINT AS n_item, count(*)::BIGINT AS n_shared, count(*)::DOUBLE / n_item AS containment
      FROM x JOIN q USING (k, g) JOIN n USING (item_id) GROUP BY doc_id, item_id, n_item HAVING 100 * count(*) >= 80 * n_item"""
