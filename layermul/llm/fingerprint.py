"""Document fingerprints by locally consistent parsing.

Each level of the parse first names runs of one symbol, then labels every symbol by deterministic
coin tossing: the lowest bit in which it differs from its left neighbour, and the bit's value.
Repeated, this shrinks labels to a handful, so that a symbol's final label depends on a few symbols
to its left only. Local minima of the labels start phrases, phrases are named by a hash of their
symbols, and the names are the next level's symbols. Equal substrings therefore share all names but
a few at their ends, at whatever offset they stand.

The fingerprint is a minimum sketch of the names of `lowest` and higher levels: names fall into
`places` by hash, each place keeps its least. Likeness is the share of equal places among those
that are used by either.

Edge cases: null text is empty; the empty text's fingerprint has no used place, and two such are
wholly alike; very short texts have at least their last name; repeated rows each get their own
result row, in the order of doc_id and then text; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .scratch import bound_arrow, table
from .textscan import mix, small_batches

#: Names of phrases of about three to the power of this many bytes enter the sketch.
LOWEST = 3
PLACES = 64
_U = np.uint64
_LEFT = _U(0x9FB21C651E98DF25)


def _lowest_bit(x: np.ndarray) -> np.ndarray:
    """Place of the lowest set bit; x has no zero."""
    return np.bitwise_count((x & (~x + x.dtype.type(1))) - x.dtype.type(1))


def _coin_labels(symbols: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Labels below 6 that differ between neighbours, if neighbouring symbols of a text differ; each
    text's first symbol is taken against its own complement."""
    x = symbols
    for _ in range(4):  # 64 bits -> below 128 -> 14 -> 8 -> 6
        left = np.empty_like(x)
        left[1:] = x[:-1]
        left[first] = ~x[first]
        bit = _lowest_bit(x ^ left).astype(np.uint8)
        x = (bit << np.uint8(1)) | ((x >> bit.astype(x.dtype)) & x.dtype.type(1)).astype(np.uint8)
    return x


def _named_runs(symbols: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Runs of one symbol become one symbol that also names the run's length; and the texts' starts."""
    new = np.empty(len(symbols), bool)
    new[1:] = symbols[1:] != symbols[:-1]
    new[first] = True
    at = np.flatnonzero(new)
    if len(at) == len(symbols):
        return symbols, first
    length = np.diff(np.append(at, len(symbols)))
    many = np.flatnonzero(length > 1)
    out = symbols[at].astype(_U)
    out[many] = mix(out[many] ^ (length[many].astype(_U) * _LEFT))
    return out, np.searchsorted(at, first)


def _phrases(symbols: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Names of the phrases of one level, and the texts' starts among them."""
    labels = _coin_labels(symbols, first)
    start = np.zeros(len(symbols), bool)
    start[1:-1] = (labels[1:-1] < labels[:-2]) & (labels[1:-1] < labels[2:])
    start[np.append(first[1:], len(symbols)) - 1] = False
    start[first] = True
    at = np.flatnonzero(start)
    length = np.diff(np.append(at, len(symbols)))
    place = np.arange(len(symbols)) - np.repeat(at, length)
    weighed = mix(symbols.astype(_U) + _U(1)) * _ODD[np.minimum(place, len(_ODD) - 1)]
    return mix(np.add.reduceat(weighed, at) ^ length.astype(_U)), np.searchsorted(at, first)


_ODD = mix(np.arange(1, 65, dtype=_U)) | _U(1)  # a phrase has at most a dozen symbols or so; further ones share a factor
_AT_ONCE = 1 << 20  # bytes of texts parsed together


def _parsed(texts: list[bytes], lowest: int, places: int) -> np.ndarray:
    out = np.full(len(texts) * places, ~_U(0))
    who = np.flatnonzero([len(t) > 0 for t in texts])  # the texts still being parsed
    symbols = np.frombuffer(b"".join(texts), np.uint8)
    first = np.cumsum([0] + [len(texts[i]) for i in who])[:-1].astype(np.int64)
    level = 0
    while len(who):
        symbols, first = _phrases(*_named_runs(symbols, first))
        level += 1
        count = np.diff(np.append(first, len(symbols)))
        done = count == 1
        told = np.repeat(done | (level >= lowest), count)
        names = mix(symbols[told] + _U(level))
        slot = np.repeat(who, count)[told] * places + (names % _U(places)).astype(np.int64)
        np.minimum.at(out, slot, names >> _U(1))
        if done.any():
            symbols, who, count = symbols[np.repeat(~done, count)], who[~done], count[~done]
            first = np.cumsum(np.concatenate([[0], count]))[:-1]
    return out.reshape(len(texts), places)


def sketches(texts: list[bytes], lowest: int = LOWEST, places: int = PLACES) -> np.ndarray:
    """For each text `places` 64-bit minima of its phrase names; the greatest number marks an unused place."""
    out, i = [np.empty((0, places), _U)], 0
    while i < len(texts):
        j, size = i + 1, len(texts[i])
        while j < len(texts) and size + len(texts[j]) <= _AT_ONCE:
            size += len(texts[j])
            j += 1
        out.append(_parsed(texts[i:j], lowest, places))
        i = j
    return np.concatenate(out)


def sketch(text: bytes, lowest: int = LOWEST, places: int = PLACES) -> np.ndarray:
    return _parsed([text], lowest, places)[0]


def likeness_rows(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Row by row the share of equal places among those that either uses; 1 where none is used."""
    used = (x != ~_U(0)) | (y != ~_U(0))
    n = used.sum(axis=1)
    return np.where(n > 0, ((x == y) & used).sum(axis=1) / np.maximum(n, 1), 1.0)


def likeness(x: np.ndarray, y: np.ndarray) -> float:
    return float(likeness_rows(x[None], y[None])[0])


def spelled(x: np.ndarray) -> str:
    """Eight hex digits a place."""
    return (x >> _U(31)).astype(">u4").tobytes().hex()


def _with_next(lowest: int, places: int):
    """Rows of one block of documents in order, the first of the next block at its end (last = True)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None  # the row that waits for its successor: doc_id, text, sketch
        for batch in small_batches(batches, "text"):
            ids, texts, last = (batch.column(i).to_pylist() for i in range(1, 4))
            end = last.index(True) + 1 if True in last else len(texts)  # further rows of the next block's first document don't count
            ids, texts = ids[:end], texts[:end]
            own = sketches([t.encode() for t in texts], lowest, places)
            if held is not None:
                ids, texts, own = [held[0], *ids], [held[1], *texts], np.concatenate([held[2][None], own])
            halves = [len(t) // 2 for t in texts[:-1]]
            edited = [(t[: len(t) - h] + n[:h]).encode() for t, n, h in zip(texts, texts[1:], halves, strict=False)]
            changed = sketches(edited, lowest, places)
            cols = [ids[:-1], [len(t) for t in texts[:-1]], [hashlib.sha256(e).hexdigest() for e in edited], [spelled(x) for x in own[:-1]], [spelled(x) for x in changed],
                    likeness_rows(own[:-1], changed), likeness_rows(own[:-1], own[1:])]
            yield pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(cols, SCHEMA, strict=True)], schema=SCHEMA)
            if last[end - 1]:
                return
            held = ids[-1], texts[-1], own[-1]

    return run


SCHEMA = pa.schema([("doc_id", pa.int64()), ("n_chars", pa.int64()), ("edited_sha256", pa.string()), ("fingerprint", pa.string()), ("edited_fingerprint", pa.string()), ("near_edited", pa.float64()), ("near_next", pa.float64())])
_RESULT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def fingerprints_with_next(docs: DataFrame, rows_per_block: int = 1 << 15, lowest: int = LOWEST, places: int = PLACES) -> DataFrame:
    """docs: doc_id, text. Documents lie in blocks of consecutive doc_id, one a partition and streamed in
    order; the first row of a block is also dealt to the block before, so each block knows its
    successor without a global window. The driver holds one id for each block."""
    spark = docs.sparkSession
    bound_arrow(spark)
    rows = docs.select(F.col("doc_id").cast("long"), F.coalesce("text", F.lit("")).alias("text"))
    blocks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-docs.count() // rows_per_block))
    key = F.coalesce("doc_id", F.lit(-(2**63)))  # null ids stand first
    ranges = rows.select(key.alias("key")).repartitionByRange(blocks, "key").groupBy(F.spark_partition_id().alias("range"))
    starts = np.sort(ranges.agg(F.min("key").alias("start")).select("start").toArrow()["start"].to_numpy())  # ids alone are shuffled for it
    if not len(starts):
        return rows.limit(0).mapInArrow(lambda b: iter(()), _RESULT)
    n = len(starts)
    listed = F.split(F.lit(",".join(map(str, starts.tolist()))), ",").cast("array<bigint>")  # folded to one literal
    placed = rows.withColumn("block", _place(key, listed, n) - 1)
    own, before = (F.struct(b.cast("int").alias("block"), F.lit(last).alias("last")) for b, last in ((F.col("block"), False), (F.pmod(F.col("block") - 1, F.lit(n)), True)))
    both = F.when(F.get(listed, F.col("block")) == key, F.array(own, before)).otherwise(F.array(own))
    dealt = placed.select("doc_id", "text", F.explode(both).alias("b")).select("b.block", "doc_id", "text", "b.last")
    dealt = dealt.repartitionById(n, "block").sortWithinPartitions("block", "last", F.col("doc_id").asc_nulls_first(), "text")
    return dealt.mapInArrow(_with_next(lowest, places), _RESULT)


def _place(key, listed, n: int):
    """How many of the n listed ids are at or below the key, by halving."""
    state = F.struct(F.lit(0).alias("lo"), F.lit(n).alias("hi"))
    steps = F.sequence(F.lit(1), F.lit(max(1, n.bit_length())))

    def halve(s, _):
        mid = F.floor((s["lo"] + s["hi"]) / 2).cast("int")
        up = F.get(listed, mid) <= key
        return F.struct(F.when((s["lo"] < s["hi"]) & up, mid + 1).otherwise(s["lo"]).alias("lo"), F.when((s["lo"] < s["hi"]) & ~up, mid).otherwise(s["hi"]).alias("hi"))

    return F.aggregate(steps, state, halve, lambda s: s["lo"])


def op10_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints_with_next(table(spark, sf_dir, "documents").select("doc_id", "text"))
